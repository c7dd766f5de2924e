"""Secrets in texts: runs of key characters, sorted by a random forest.

Every run of at least ``least`` letters, digits and ``_ - + / =`` is a candidate.  The
forest looks at its length, its make-up, how likely its character transitions are in
this corpus, how much of it common words of this corpus cover, whether it stands in a
path, and the words beside it.  It is trained on labelled findings; where there are
none, on candidates whose form or assignment tells what they are.  Transitions and
words are counted over all documents.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenkeel.llm import _bytes, _store


@dataclass(frozen=True)
class Settings:
    least: int = 16
    #: Most common words of 3 to 8 bytes that make the dictionary.
    dictionary: int = 20_000
    #: Most labelled findings of either class that the forest is grown on.
    most_findings: int = 8_000
    trees: int = 24
    depth: int = 8
    seed: int = 11


_RUN = np.zeros(256, dtype=bool)
_RUN[[*range(48, 58), *range(65, 91), *range(97, 123), *map(ord, "_-+/=")]] = True
_KINDS = np.zeros(256, dtype=np.int8)
_KINDS[48:58], _KINDS[65:91], _KINDS[97:123] = 1, 2, 3
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_NAMED = re.compile(rb"(?i)(key|token|secret|passw|pwd|auth|credential)")
_KNOWN = re.compile(rb"^(AKIA[0-9A-Z]{16}|gh[pousr]_[0-9A-Za-z]{36}|sk_live_[0-9A-Za-z]{16,}|xox[bp]-[0-9A-Za-z-]{10,})$")

FEATURES = ["length", "digits", "capitals", "small", "hex", "changes", "entropy", "transitions", "coverage", "path", "named_before", "assigned", "quoted", "named_after"]


def runs(data: np.ndarray, offsets: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and text of every candidate; ``=`` at the start is not part of one."""
    inside = np.zeros(len(data) + 2, dtype=bool)
    inside[1:-1] = _RUN[data]
    edge = np.zeros(len(data) + 1, dtype=bool)
    edge[offsets] = True
    start = np.flatnonzero(inside[1:] & (~inside[:-1] | edge))
    end = np.flatnonzero(inside[:-1] & (~inside[1:] | edge))
    long = end - start >= least
    start, end = start[long], end[long]
    for i in range(len(start)):  # the value of an assignment without blanks: key=value
        raw = data[start[i] : end[i]].tobytes()
        cut = raw.rstrip(b"=").rfind(b"=") + 1
        if cut:
            start[i] += cut
    long = end - start >= least
    return start[long], end[long], np.searchsorted(offsets, start[long], side="right") - 1


@dataclass
class Corpus:
    """What all documents say: log probabilities of byte pairs, and common words."""

    transitions: np.ndarray
    words: frozenset[bytes]

    def coverage(self, raw: bytes) -> float:
        low, at, covered = raw.lower(), 0, 0
        while at < len(low):
            for n in range(min(8, len(low) - at), 2, -1):
                if low[at : at + n] in self.words:
                    covered, at = covered + n, at + n
                    break
            else:
                at += 1
        return covered / max(1, len(low))


def features(data: np.ndarray, low: int, high: int, start: int, end: int, corpus: Corpus) -> list[float]:
    b = data[start:end]
    n = len(b)
    kinds = _KINDS[b]
    counts = np.bincount(b, minlength=256)
    p = counts[counts > 0] / n
    before, after = data[max(low, start - 24) : start].tobytes(), data[end : min(high, end + 16)].tobytes()
    raw, c = b.tobytes(), _LOWER[b].astype(np.int64)
    tail = before.rstrip()
    return [
        float(n),
        float((kinds == 1).mean()),
        float((kinds == 2).mean()),
        float((kinds == 3).mean()),
        sum(x in b"0123456789abcdefABCDEF" for x in raw) / n,
        float((kinds[1:] != kinds[:-1]).mean()),
        float(-(p * np.log2(p)).sum()),
        float(corpus.transitions[c[:-1], c[1:]].mean()),
        corpus.coverage(raw),
        float(raw.count(b"/") / n + (before[-1:] == b"/")),
        float(bool(_NAMED.search(before))),
        float(tail.rstrip(b"\"'").rstrip().endswith((b"=", b":"))),
        float(before[-1:] in (b'"', b"'")),
        float(bool(_NAMED.search(after))),
    ]


def corpus_counts(docs: DataFrame, s: Settings) -> Corpus:
    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pairs, found = np.zeros(65536, dtype=np.int64), []
        for batch in batches:
            for piece in _bytes.pieces(batch.column(0)):
                data, offsets = _bytes.buffers(piece)
                low = _LOWER[data]
                pairs += np.bincount(low[:-1].astype(np.int64) << 8 | low[1:], minlength=65536) if len(low) > 1 else 0
                w = _bytes.word_hashes(data, offsets)
                short = (w.end - w.start >= 3) & (w.end - w.start <= 8)
                st, n = w.start[short], (w.end - w.start)[short]
                padded = np.concatenate([low, np.zeros(8, np.uint8)])
                packed = np.zeros(len(st), dtype=np.uint64)
                for k in range(8):
                    packed |= np.where(n > k, padded[st + k], 0).astype(np.uint64) << np.uint64(8 * k)
                found.append(np.unique(packed, return_counts=True))
                if len(found) > 64:
                    found = [_add(found)]
        words, counts = _add(found)
        there = np.flatnonzero(pairs)
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([np.zeros(len(there), bool), np.ones(len(words), bool)])), pa.array(np.concatenate([there, words.astype(np.int64)])), pa.array(np.concatenate([pairs[there], counts]), pa.int64())], ["word", "what", "n"])

    counted = docs.select("text").mapInArrow(partial, "word boolean, what bigint, n bigint").groupBy("word", "what").agg(F.sum("n").alias("n"))
    counted = _store.materialise(counted)
    pairs = counted.where("not word").select("what", "n").toPandas()
    top = counted.where("word").orderBy(F.desc("n"), "what").limit(s.dictionary).select("what").toPandas()
    table = np.full(65536, 0.5)
    table[pairs["what"].to_numpy()] += pairs["n"].to_numpy()
    table = table.reshape(256, 256)
    words = frozenset(int(x).to_bytes(8, "little", signed=True).rstrip(b"\0") for x in top["what"])
    return Corpus(np.log(table / table.sum(1, keepdims=True)), words)


def _add(found: list) -> tuple[np.ndarray, np.ndarray]:
    if not found:
        return np.empty(0, np.uint64), np.empty(0, np.int64)
    words, inverse = np.unique(np.concatenate([f[0] for f in found]), return_inverse=True)
    return words, np.bincount(inverse, weights=np.concatenate([f[1] for f in found]), minlength=len(words)).astype(np.int64)


def candidates(docs: DataFrame, corpus: Corpus, s: Settings) -> DataFrame:
    """doc_id, start, stop (bytes), known (1 known form or named assignment of mixed
    characters, 0 letters or digits only, null can't tell), x (features)."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    held = docs.sparkSession.sparkContext.broadcast(corpus)

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, at = batch.column("doc_id"), 0
            for piece in _bytes.pieces(batch.column("text")):
                data, offsets = _bytes.buffers(piece)
                start, end, owner = runs(data, offsets, s.least)
                x, known = [], []
                for a, b, o in zip(start.tolist(), end.tolist(), owner.tolist(), strict=True):
                    f = features(data, offsets[o], offsets[o + 1], a, b, held.value)
                    x.append(f)
                    named = f[10] and f[11]
                    known.append(1 if _KNOWN.match(data[a:b].tobytes()) or named and f[1] > 0 else 0 if f[1] in (0.0, 1.0) and not named else None)
                yield pa.RecordBatch.from_arrays(
                    [ids.take(pa.array(owner + at)), pa.array(start - offsets[owner], pa.int64()), pa.array(end - offsets[owner], pa.int64()), pa.array(known, pa.int32()), pa.array(x, pa.list_(pa.float32()))],
                    ["doc_id", "start", "stop", "known", "x"],
                )
                at += len(piece)

    return docs.select("doc_id", "text").mapInArrow(find, f"doc_id {kind}, start bigint, stop bigint, known int, x array<float>")


class Forest:
    """Trees on quantised features, each grown on a resample with a random subset of the
    features at every split."""

    def __init__(self, x: np.ndarray, y: np.ndarray, s: Settings):
        rng = np.random.default_rng(s.seed)
        self.cuts = [np.unique(np.quantile(x[:, j], np.linspace(0.02, 0.98, 31))) for j in range(x.shape[1])]
        binned = np.stack([np.searchsorted(c, x[:, j], side="right") for j, c in enumerate(self.cuts)], 1)
        self.trees = []
        for _ in range(s.trees):
            rows = rng.integers(0, len(y), len(y))
            nodes: list[tuple] = []
            self._grow(binned[rows], y[rows], s.depth, rng, nodes)
            self.trees.append(np.array(nodes))

    def _grow(self, b, y, depth, rng, nodes) -> int:
        me, share = len(nodes), float(y.mean())
        nodes.append((-1.0, 0.0, 0.0, 0.0, share))
        if depth == 0 or len(y) < 8 or share in (0.0, 1.0):
            return me
        best = (1e-9, -1, 0)
        for j in rng.choice(b.shape[1], max(2, int(np.sqrt(b.shape[1]) + 1)), replace=False):
            n = np.bincount(b[:, j], minlength=33).cumsum()
            k = np.bincount(b[:, j], weights=y, minlength=33).cumsum()
            with np.errstate(divide="ignore", invalid="ignore"):
                left, right = k * (1 - k / n), (k[-1] - k) * (1 - (k[-1] - k) / (n[-1] - n))
            gain = k[-1] * (1 - share) - np.nan_to_num(left) - np.nan_to_num(right)
            gain[(n == 0) | (n == n[-1])] = 0
            if gain.max() > best[0]:
                best = (gain.max(), j, int(gain.argmax()))
        if best[1] < 0:
            return me
        goes = b[:, best[1]] <= best[2]
        l = self._grow(b[goes], y[goes], depth - 1, rng, nodes)  # noqa: E741
        r = self._grow(b[~goes], y[~goes], depth - 1, rng, nodes)
        nodes[me] = (float(best[1]), float(best[2]), float(l), float(r), share)
        return me

    def predict(self, x: np.ndarray) -> np.ndarray:
        b = np.stack([np.searchsorted(c, x[:, j], side="right") for j, c in enumerate(self.cuts)], 1)
        total, rows = np.zeros(len(x)), np.arange(len(x))
        for t in self.trees:
            at = np.zeros(len(x), dtype=np.int64)
            while True:
                j = t[at, 0].astype(np.int64)
                if (j < 0).all():
                    break
                nxt = np.where(b[rows, np.maximum(j, 0)] <= t[at, 1], t[at, 2], t[at, 3]).astype(np.int64)
                at = np.where(j < 0, at, nxt)
            total += t[at, 4]
        return total / max(1, len(self.trees))


def train(found: DataFrame, s: Settings = Settings()) -> Forest | None:
    """On labelled findings (``known`` 0 or 1); None without both classes."""
    parts = []
    for label in (0, 1):
        own = _store.sample_by_hash(found.where(F.col("known") == label), s.most_findings, "doc_id", "start")
        parts.append(own.select("known", "x"))
    rows = parts[0].unionByName(parts[1]).toPandas()
    if rows["known"].nunique() < 2:
        return None
    return Forest(np.stack(rows["x"].to_numpy()).astype(float), rows["known"].to_numpy().astype(float), s)


def scan(docs: DataFrame, s: Settings = Settings(), findings: DataFrame | None = None) -> DataFrame:
    """doc_id, start, stop (byte range in the UTF-8 text), p_secret, secret for every
    candidate of every row.

    ``findings`` (doc_id, start, stop, known) replaces the labels that form gives.  Null
    and empty texts have no candidates.  Repeated rows give repeated findings.  Without
    labels of both classes only known forms and named assignments are secret.
    """
    found = _store.materialise(candidates(docs, corpus_counts(docs, s), s))
    labelled = found
    if findings is not None:
        labelled = found.drop("known").join(findings.select("doc_id", "start", "stop", "known"), ["doc_id", "start", "stop"])
    forest = train(labelled, s)
    if forest is None:
        p = F.coalesce(F.col("known"), F.lit(0)).cast("double")
        return found.select("doc_id", "start", "stop", p.alias("p_secret"), (p >= 0.5).alias("secret"))
    held = found.sparkSession.sparkContext.broadcast(forest)

    @F.arrow_udf("double")
    def judge(x: pa.Array) -> pa.Array:
        if not len(x):
            return pa.array([], pa.float64())
        return pa.array(np.round(held.value.predict(x.flatten().to_numpy().reshape(len(x), -1).astype(float)), 6))

    return found.select("doc_id", "start", "stop", judge("x").alias("p_secret")).withColumn("secret", F.col("p_secret") >= 0.5)


def op4_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(_store.table(spark, sf_dir, "documents"))
