"""Byte-level BPE encoding by a lazily determinised transducer, and streaming decode.

Each prefix of a word has exactly one encoding, and an encoding of a longer prefix is
one of a shorter prefix and one more token that may stand after its last one.  A
nondeterministic transducer hence keeps, for every prefix whose rest so far begins some
token, the last token, the place in the token tree and the tokens not yet emitted.  Sets
of such branches are the states of the deterministic transducer; a step is computed the
first time it is taken and kept.  What all branches agree on is emitted, and a branch
dies as soon as its rest begins no token, so the delay is at most the longest token.

Two tokens may be neighbours if no merge ever joins across their border.  The tokens
that touch the border are the right edge of the left one's merge tree and the left edge
of the right one's, each present from its own merge to the merge that takes it in.

Decoding goes token by token; an incremental UTF-8 state machine holds back at most
three bytes of an unfinished character and gives U+FFFD for what can't be one.
"""

from __future__ import annotations

import base64
from array import array
from collections.abc import Iterator
from dataclasses import dataclass
from pathlib import Path

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenkeel.llm import _bytes, _store

#: The public pre-tokenisation pattern of the vocabulary files.
PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""


@dataclass(frozen=True)
class Settings:
    #: Ranks file: a base64 token and its rank a line.
    vocabulary: str = "/opt/tokenizers/byte_bpe_50k.tiktoken"
    pattern: str = PATTERN
    #: Words, and transducer states, that a worker keeps at most: the first ones, among which
    #: are the common ones; others are computed whenever they occur.  It changes no result.
    kept_words: int = 150_000
    kept_states: int = 120_000


class Vocabulary:
    """Token bytes, merges and merge trees from a ranks file."""

    #: Pairs of tokens whose neighbourhood is remembered; then it begins anew.
    kept_neighbours = 200_000

    def __init__(self, path: str):
        pairs = (line.split() for line in Path(path).read_bytes().splitlines() if line.strip())
        self.rank = {base64.b64decode(t): int(r) for t, r in pairs}
        self.token = {r: t for t, r in self.rank.items()}
        self.merge: dict[tuple[int, int], int] = {}
        self.parts: dict[int, tuple[int, int]] = {}
        for t, r in sorted(self.rank.items(), key=lambda x: x[1]):
            if len(t) > 1:
                pieces = self._reduce(t, r)
                if len(pieces) == 2:
                    self.parts[r] = pieces
                    self.merge[pieces] = r
        # tokens that BPE can end with: single bytes and those with a merge tree
        usable = [t for t, r in self.rank.items() if len(t) == 1 or r in self.parts]
        self.children: list[dict[int, int]] = [{}]
        self.ends: list[int] = [-1]
        for t in usable:
            at = 0
            for b in t:
                nxt = self.children[at].get(b)
                if nxt is None:
                    nxt = self.children[at][b] = len(self.children)
                    self.children.append({})
                    self.ends.append(-1)
                at = nxt
            self.ends[at] = self.rank[t]
        self._edges: tuple[dict[int, list], dict[int, list]] = ({}, {})
        self._neighbours: dict[int, bool] = {}

    def _reduce(self, t: bytes, limit: int) -> tuple[int, ...]:
        """BPE of ``t`` with the merges under ``limit``."""
        s = [self.rank[t[i : i + 1]] for i in range(len(t))]
        while len(s) > 1:
            best, at = min((self.merge.get(p, limit), i) for i, p in enumerate(zip(s, s[1:], strict=False)))
            if best >= limit:
                break
            s[at : at + 2] = [best]
        return tuple(s)

    def _edge(self, token: int, side: int) -> list[tuple[int, float]]:
        """(token, rank of the merge that takes it in) along one edge of the merge tree."""
        found = self._edges[side].get(token)
        if found is None:
            found, t, gone = [], token, float("inf")
            while True:
                found.append((t, gone))
                if t not in self.parts:
                    break
                t, gone = self.parts[t][side], t
            self._edges[side][token] = found
        return found

    def neighbours(self, a: int, b: int) -> bool:
        """Whether ``b`` may follow ``a`` in an encoding."""
        known = self._neighbours.get(a << 32 | b)
        if known is None:
            if len(self._neighbours) > self.kept_neighbours:
                self._neighbours.clear()
            known = True
            for x, x_gone in self._edge(a, 1):
                for y, y_gone in self._edge(b, 0):
                    joint = self.merge.get((x, y))
                    # of equal merges the left one comes first
                    if joint is not None and joint < x_gone and joint <= y_gone:
                        known = False
            self._neighbours[a << 32 | b] = known
        return known


class Transducer:
    """Words to tokens; states and steps come into being as they are needed."""

    def __init__(self, vocabulary: Vocabulary, kept_states: int = 100_000):
        self.v, self.kept_states = vocabulary, kept_states
        self._begin()

    def _begin(self) -> None:
        start = ((-1, 0, ()),)
        self.number = {start: 0}
        self.branches = [start]
        self.final: list[tuple[int, ...]] = [()]
        # A state goes by 256 times its number. A step that emits nothing is the next state alone.
        self.steps: dict[int, int | tuple[int, tuple[int, ...]]] = {}

    def _step(self, state: int | tuple, byte: int) -> int | tuple[int, tuple[int, ...]]:
        v, after, done, kept = self.v, [], None, state.__class__ is int
        for last, node, pending in self.branches[state >> 8] if kept else state:
            child = v.children[node].get(byte)
            if child is None:
                continue
            if v.children[child]:
                after.append((last, child, pending))
            token = v.ends[child]
            if token >= 0 and (last < 0 or v.neighbours(last, token)):
                done = (token, 0, (*pending, token))
        if done is None:
            raise ValueError(f"byte {byte} is not in the vocabulary")
        after.append(done)
        agreed = 0
        first = after[0][2]
        while agreed < len(first) and all(len(p) > agreed and p[agreed] == first[agreed] for _, _, p in after):
            agreed += 1
        key = tuple((t, n, p[agreed:]) for t, n, p in after)
        to = self.number.get(key)
        if to is None:
            if not kept or len(self.branches) >= self.kept_states:
                return key, first[:agreed]  # a state that is not kept goes by its branches
            to = self.number[key] = len(self.branches) << 8
            self.branches.append(key)
            self.final.append(key[-1][2])
        made = (to, first[:agreed]) if agreed else to
        if kept:
            self.steps[state | byte] = made
        return made

    def feed(self, state: int, data: bytes) -> tuple[int, list[int]]:
        """State after ``data`` and the tokens that are certain by then."""
        out: list[int] = []
        steps = self.steps
        for byte in data:
            made = steps.get(state | byte) if state.__class__ is int else None
            if made is None:
                made = self._step(state, byte)
            if made.__class__ is int:
                state = made
            else:
                state, emitted = made
                out += emitted
        return state, out

    def encode(self, word: bytes) -> list[int]:
        state, out = self.feed(0, word)
        out += self.final[state >> 8] if state.__class__ is int else state[-1][2]
        return out


class Encoder(dict):
    """Texts to tokens; a dictionary from a word to its number in flat token arrays."""

    def __init__(self, settings: Settings = Settings(), vocabulary: Vocabulary | None = None):
        super().__init__()
        self.settings = settings
        self.vocabulary = vocabulary or Vocabulary(settings.vocabulary)
        self.transducer = Transducer(self.vocabulary, settings.kept_states)
        self.find = regex.compile(settings.pattern).findall
        self.flat, self.starts = array("i"), array("q", [0])

    def __missing__(self, word: str) -> int:
        self.flat.extend(self.transducer.encode(word.encode()))
        self.starts.append(len(self.flat))
        number = len(self.starts) - 2
        if len(self) < self.settings.kept_words:
            self[word] = number
        return number

    def encode_all(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """All tokens, and where each text's tokens begin."""
        del self.starts[len(self) + 1 :]  # words of the last texts that are not kept
        del self.flat[self.starts[-1] :]
        numbers, counts = array("q"), [0]
        for t in texts:
            if t:
                numbers.extend(map(self.__getitem__, self.find(t)))
            counts.append(len(numbers))
        starts, flat = np.array(self.starts, dtype=np.int64), np.array(self.flat, dtype=np.int32)
        n = np.frombuffer(numbers, dtype=np.int64) if numbers else np.empty(0, np.int64)
        lengths = starts[n + 1] - starts[n]
        ends = np.concatenate(([0], np.cumsum(lengths)))
        place = np.repeat(starts[n] - ends[:-1], lengths) + np.arange(ends[-1])
        return flat[place] if len(place) else np.empty(0, np.int32), ends[np.array(counts)]

    def encode(self, text: str) -> list[int]:
        return self.encode_all([text])[0].tolist()


# UTF-8 as a state machine: class of a byte, then state by (state, class).
# States: 0 accept, 1 reject, 2-4 so many continuation bytes to come (less 1), 5-8 special second bytes.
def _machine() -> tuple[np.ndarray, list[dict[int, int]]]:
    kind = np.zeros(256, dtype=np.int8)
    for low, high, c in ((0x80, 0x8F, 1), (0x90, 0x9F, 2), (0xA0, 0xBF, 3), (0xC0, 0xC1, 11), (0xC2, 0xDF, 4), (0xE0, 0xE0, 5), (0xE1, 0xEC, 6), (0xED, 0xED, 7), (0xEE, 0xEF, 6), (0xF0, 0xF0, 8), (0xF1, 0xF3, 9), (0xF4, 0xF4, 10), (0xF5, 0xFF, 11)):
        kind[low : high + 1] = c
    more = {1: 0, 2: 0, 3: 0}
    steps = [{} for _ in range(9)]
    steps[0] = {0: 0, 4: 2, 5: 5, 6: 3, 7: 6, 8: 7, 9: 4, 10: 8}
    steps[2] = more
    steps[3] = dict.fromkeys(more, 2)
    steps[4] = dict.fromkeys(more, 3)
    steps[5], steps[6] = {3: 2}, {1: 2, 2: 2}
    steps[7], steps[8] = {2: 3, 3: 3}, {1: 3}
    return kind, steps


_KIND, _STEPS = _machine()


class Decoder:
    """Tokens to text in any portions; ``feed`` gives the characters that are complete."""

    def __init__(self, vocabulary: Vocabulary):
        size = max(vocabulary.token) + 1
        self.bytes = [vocabulary.token.get(i, b"") for i in range(size)]
        self.held = b""

    def feed(self, tokens) -> str:
        data = self.held + b"".join(map(self.bytes.__getitem__, tokens))
        whole = self._whole(data)
        try:
            text, self.held = data[:whole].decode("utf-8"), data[whole:]
            return text
        except UnicodeDecodeError:
            text, self.held = self._walk(data)
            return text

    def finish(self) -> str:
        rest, self.held = self.held, b""
        return "�" if rest else ""

    @staticmethod
    def _whole(data: bytes) -> int:
        """Where an unfinished character at the end begins."""
        for back in range(1, min(3, len(data)) + 1):
            kind = int(_KIND[data[-back]])
            if kind in (1, 2, 3):
                continue
            state = 0
            for b in data[len(data) - back :]:
                state = _STEPS[state].get(int(_KIND[b]), 1)
                if state == 1:
                    return len(data)
            return len(data) - back if state else len(data)
        return len(data)

    @staticmethod
    def _walk(data: bytes) -> tuple[str, bytes]:
        """Byte by byte, for data with errors: each longest wrong beginning gives U+FFFD."""
        out, state, start, i = [], 0, 0, 0
        while i < len(data):
            to = _STEPS[state].get(int(_KIND[data[i]]), 1)
            if to == 1:
                out.append("�")
                if state == 0:
                    i += 1  # else the byte may begin another character
                state, start = 0, i
                continue
            i, state = i + 1, to
            if state == 0:
                out.append(data[start:i].decode("utf-8"))
                start = i
        return "".join(out), data[start:]


_workers: dict[Settings, tuple[Encoder, Decoder]] = {}


def _tools(settings: Settings) -> tuple[Encoder, Decoder]:
    if settings not in _workers:
        encoder = Encoder(settings)
        _workers[settings] = encoder, Decoder(encoder.vocabulary)
    return _workers[settings]


def _encoded(settings: Settings):
    kind = pa.struct([("tokens", pa.list_(pa.int32())), ("round_trip", pa.bool_())])

    @F.arrow_udf("tokens array<int>, round_trip boolean")
    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        encoder, decoder = _tools(settings)
        for texts in batches:
            for piece in _bytes.pieces(texts):  # each goes out by itself: a worker holds the tokens of one
                there = piece.to_pylist()
                tokens, at = encoder.encode_all(there)
                same = []
                for i, t in enumerate(there):
                    own = tokens[at[i] : at[i + 1]].tolist()
                    same.append(None if t is None else decoder.feed(own) + decoder.finish() == t)
                lists = pa.ListArray.from_arrays(pa.array(at.astype(np.int32)), pa.array(tokens, pa.int32()))
                lists = pa.ListArray.from_buffers(lists.type, len(there), [pa.array([t is not None for t in there]).buffers()[1], lists.buffers()[1]], children=[lists.values])
                yield pa.StructArray.from_arrays([lists, pa.array(same, pa.bool_())], ["tokens", "round_trip"])
            if not len(texts):
                yield pa.array([], kind)
            _bytes.give_back()

    return run


def encode_documents(docs: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """doc_id, tokens, n_tokens, round_trip (whether decoding gives the text again) of
    every row.  Empty text: no tokens, true.  Null text: null tokens, 0, null.  Repeated
    rows are encoded each; other columns are ignored."""
    e = docs.select("doc_id", _encoded(settings)("text").alias("e"))
    return e.select("doc_id", "e.tokens", F.coalesce(F.size("e.tokens"), F.lit(0)).alias("n_tokens"), "e.round_trip")


def decode_documents(encoded: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """doc_id and text of every row of (doc_id, tokens); null tokens give null."""

    @F.arrow_udf("string")
    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        _, decoder = _tools(settings)
        for tokens in batches:
            yield pa.array([None if t is None else decoder.feed(t) + decoder.finish() for t in tokens.to_pylist()], pa.string())

    return encoded.select("doc_id", run("tokens").alias("text"))


def op2_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_documents(_store.table(spark, sf_dir, "documents"))
