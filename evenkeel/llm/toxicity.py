"""Toxic documents by multiple-instance learning.

A document is a bag of sentences and only the bag is labelled.  Sentence ``s`` is
toxic with probability ``p_s = sigmoid(bias + sum of the weights of its words)``; the
document with ``1 - (1 - leak) * prod(1 - p_s)``.  The leak takes up labels that no
sentence explains, so wrong labels do not teach the words, and it is left out when
documents are scored.  Words and beginnings of words whose documents' labels are far
from chance get weights, fitted by proximal gradient steps (L1).  Near copies count once in the fit, else the
rare words of a copied document with a wrong label would look toxic.

Fitting uses a sample of the labelled documents of a documented bound (``Settings``);
scoring covers every document and whole texts.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenkeel.llm import _bytes, _store


@dataclass(frozen=True)
class Settings:
    #: Most labelled documents of either class that the fit sees.
    most_toxic: int = 1000
    most_clean: int = 1500
    #: A word may get a weight if the likelihood ratio statistic of its documents'
    #: labels reaches this (twice the log of the ratio).
    least_evidence: float = 20.0
    rounds: int = 150
    l1: float = 1.5
    bag_threshold: float = 0.5
    sentence_threshold: float = 0.5


@dataclass
class Model:
    """``keys`` (sorted word hashes) with ``weights``; the bias of a sentence."""

    keys: np.ndarray
    weights: np.ndarray
    bias: float
    leak: float

    def __post_init__(self):
        self.maybe = np.zeros(1 << 16, dtype=bool)
        self.maybe[(self.keys & np.uint64(0xFFFF)).astype(np.int64)] = True

    def marked(self, hashes: np.ndarray) -> np.ndarray:
        """Positions of the hashes that have a weight."""
        likely = np.flatnonzero(self.maybe[(hashes & np.uint64(0xFFFF)).astype(np.int64)])
        if not len(self.keys):
            return likely
        at = np.minimum(np.searchsorted(self.keys, hashes[likely]), len(self.keys) - 1)
        return likely[self.keys[at] == hashes[likely]]

    def weight(self, hashes: np.ndarray) -> np.ndarray:
        return self.weights[np.searchsorted(self.keys, hashes)]


#: Beginnings of so many bytes are features beside the whole words.
_BEGINNINGS = (4, 5)


def _features(w: _bytes.Words) -> tuple[np.ndarray, np.ndarray]:
    """Feature hashes and the word that each belongs to."""
    word = np.arange(len(w.hash))
    parts, owners = [w.hash], [word]
    for h in w.prefix:
        there = h != 0
        parts.append(h[there])
        owners.append(word[there])
    return np.concatenate(parts), np.concatenate(owners)


def _bags(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Feature hashes, and for each its sentence (dense over all) and document."""
    w = _bytes.word_hashes(*_bytes.buffers(pa.array(texts, pa.large_string())), _BEGINNINGS)
    doc = np.repeat(np.arange(len(texts)), np.diff(w.first))
    cut = _bytes.sentence_numbers(w)
    new = np.ones(len(cut), dtype=bool)
    new[1:] = (cut[1:] != cut[:-1]) | (doc[1:] != doc[:-1])
    h, owner = _features(w)
    return h, (np.cumsum(new) - 1)[owner], doc[owner]


def _originals(w: _bytes.Words, n: int) -> np.ndarray:
    """Texts that do not share half of a bottom-16 sketch of their long words with an
    earlier one that was kept."""
    kept, holders = np.zeros(n, dtype=bool), {}
    for i in range(n):
        own = slice(w.first[i], w.first[i + 1])
        h = np.unique(w.hash[own][w.end[own] - w.start[own] >= 8])[:16].tolist()
        shared: dict[int, int] = {}
        for x in h:
            for j in holders.get(x, ()):
                shared[j] = shared.get(j, 0) + 1
        if h and max(shared.values(), default=0) * 2 >= len(h):
            continue
        kept[i] = True
        for x in h:
            holders.setdefault(x, []).append(i)
    return kept


def _statistic(hits: np.ndarray, seen: np.ndarray, rate: float) -> np.ndarray:
    """Twice the log likelihood ratio of ``hits`` of ``seen`` against ``rate``; 0 where
    hits are no more than expected."""
    miss = seen - hits
    with np.errstate(divide="ignore", invalid="ignore"):
        g = 2 * (np.where(hits > 0, hits * np.log(hits / (seen * rate)), 0) + np.where(miss > 0, miss * np.log(miss / (seen * (1 - rate))), 0))
    return np.where(hits > seen * rate, g, 0.0)


def fit(texts: list[str], toxic: np.ndarray, settings: Settings = Settings()) -> Model:
    """Fit on labelled texts.  Without both classes the model calls nothing toxic."""
    y = np.asarray(toxic, dtype=float)
    nothing = Model(np.empty(0, np.uint64), np.empty(0), -20.0, 0.0)
    if not len(texts):
        return nothing
    kept = _originals(_bytes.word_hashes(*_bytes.buffers(pa.array(texts, pa.large_string()))), len(texts))
    texts, y = [t for t, k in zip(texts, kept, strict=True) if k], y[kept]
    if not len(texts) or y.min() == y.max():
        return nothing
    hashes, sentence, doc = _bags(texts)
    vocabulary, word = np.unique(hashes, return_inverse=True)
    by_doc = np.unique(word.astype(np.int64) * len(texts) + doc)  # each word once a document
    word_of, y_of = by_doc // len(texts), y[by_doc % len(texts)]
    seen = np.bincount(word_of, minlength=len(vocabulary)).astype(float)
    hits = np.bincount(word_of, weights=y_of, minlength=len(vocabulary))
    chosen = np.flatnonzero(_statistic(hits, seen, y.mean()) >= settings.least_evidence)
    if not len(chosen):
        return nothing
    words, seen, hits = vocabulary[chosen], seen[chosen], hits[chosen]
    place = np.full(len(vocabulary), -1)
    place[chosen] = np.arange(len(chosen))
    n_sentences, n_docs = int(sentence.max()) + 1, len(texts)
    doc_of_sentence = np.zeros(n_sentences, dtype=np.int64)
    doc_of_sentence[sentence] = doc
    used = place[word] >= 0
    once = np.unique(sentence[used] * len(words) + place[word[used]])  # and once a sentence
    sentence_of, word = once // len(words), once % len(words)

    # The sentence bias stays fixed far below zero: whatever it would explain on its own is the leak's.
    bias, leak = -6.0, float(np.clip(y.mean() / 2, 1e-3, 0.3))
    # start from how much more often than by chance a word's documents are toxic
    weights = np.log((hits + 0.5) / (seen - hits + 0.5)) - np.log(y.mean() / (1 - y.mean()))
    momentum = np.zeros(len(words))
    step = 1.0 / np.sqrt(seen)
    for _ in range(settings.rounds):
        z = np.clip(bias + np.bincount(sentence_of, weights=weights[word], minlength=n_sentences), -30, 30)
        p = 1 / (1 + np.exp(-z))
        log_clean = np.bincount(doc_of_sentence, weights=np.log1p(-p), minlength=n_docs)
        clean = np.clip((1 - leak) * np.exp(log_clean), 1e-12, 1 - 1e-9)
        # d(-log likelihood)/dz_s: p_s for a clean bag, -p_s * clean / (1 - clean) for a toxic one
        by_bag = np.where(y > 0, -clean / (1 - clean), 1.0)
        slope = np.bincount(word, weights=(p * by_bag[doc_of_sentence])[sentence_of], minlength=len(words))
        momentum = 0.8 * momentum + slope
        weights = weights - 0.2 * step * momentum
        weights = np.sign(weights) * np.maximum(np.abs(weights) - 0.2 * step * settings.l1, 0)
        explained = np.exp(log_clean)
        leak = float(np.clip((y * leak * explained / (1 - clean)).sum() / max(1.0, explained.sum()), 1e-4, 0.5))
    used = np.abs(weights) > 1e-3
    return Model(words[used], weights[used], bias, leak)


def score(texts: pa.Array, model: Model, sentence_threshold: float) -> pa.Array:
    """One struct a text: noisy-or, number of sentences with words, and the sentences
    at or above the threshold as byte ranges (UTF-8) with their probabilities."""
    out = []
    for piece in _bytes.pieces(texts):
        w = _bytes.word_hashes(*_bytes.buffers(piece), _BEGINNINGS)
        n = len(piece)
        doc = np.repeat(np.arange(n), np.diff(w.first))
        cut = _bytes.sentence_numbers(w)
        new = np.ones(len(cut), dtype=bool)
        new[1:] = (cut[1:] != cut[:-1]) | (doc[1:] != doc[:-1])
        first = np.flatnonzero(new)
        sentence = np.cumsum(new) - 1
        z = np.full(len(first), model.bias)
        seen = []
        for h in (w.hash, *w.prefix):
            at = model.marked(h)
            seen.append(np.stack([sentence[at].astype(np.uint64), h[at]], 1))
        key = np.unique(np.concatenate(seen), axis=0)  # a feature counts once a sentence, as in the fit
        if len(key):
            np.add.at(z, key[:, 0].astype(np.int64), model.weight(key[:, 1]))
        plain = 1 / (1 + np.exp(-model.bias))
        p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        # A sentence with no known word says nothing: it is left out of the product.
        p_used = np.where(z == model.bias, 0.0, np.maximum(p - plain, 0.0))
        doc_of = doc[first]
        bag = -np.expm1(np.bincount(doc_of, weights=np.log1p(-np.minimum(p_used, 1 - 1e-12)), minlength=n))
        sentences = np.bincount(doc_of, minlength=n)
        bad = np.flatnonzero(p_used >= sentence_threshold)
        last = np.append(first[1:], len(w.hash)) - 1
        bad_doc = doc_of[bad]
        bounds = np.searchsorted(bad_doc, np.arange(n + 1)).astype(np.int32)
        spans = pa.StructArray.from_arrays(
            [pa.array(w.start[first[bad]] - w.offsets[bad_doc], pa.int64()), pa.array(w.end[last[bad]] - w.offsets[bad_doc], pa.int64()), pa.array(np.round(p_used[bad], 6))],
            ["start", "stop", "p"],
        )
        out.append(pa.StructArray.from_arrays([pa.array(np.round(bag, 6)), pa.array(sentences, pa.int32()), pa.ListArray.from_arrays(pa.array(bounds), spans)], ["p", "sentences", "offending"]))
    kind = pa.struct([("p", pa.float64()), ("sentences", pa.int32()), ("offending", pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64()), ("p", pa.float64())])))])
    return pa.concat_arrays([x.cast(kind) for x in out]) if out else pa.array([], kind)


_SCORE = "p double, sentences int, offending array<struct<start bigint, stop bigint, p double>>"


def train(docs: DataFrame, labels: DataFrame, settings: Settings = Settings()) -> Model:
    """Fit on at most ``most_toxic`` + ``most_clean`` labelled documents, chosen by a
    hash of doc_id.  A doc_id labelled both ways counts as toxic; null labels, ids
    and texts are passed over."""
    by_id = _store.materialise(labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic")))
    chosen = None
    for toxic, most in ((1, settings.most_toxic), (0, settings.most_clean)):
        part = _store.sample_by_hash(by_id.where(F.col("toxic") == toxic), most, "doc_id")
        chosen = part if chosen is None else chosen.unionByName(part)
    ids = F.broadcast(chosen)  # bounded by the settings
    rows = docs.select("doc_id", "text").where("text is not null").join(ids, "doc_id").orderBy("doc_id").toPandas()
    model = fit(rows["text"].tolist(), rows["toxic"].to_numpy(), settings)
    _bytes.give_back()
    return model


def _scored(docs: DataFrame, model: Model, settings: Settings, name: str) -> DataFrame:
    held = docs.sparkSession.sparkContext.broadcast(model)

    @F.arrow_udf(_SCORE)
    def judge(texts: pa.Array) -> pa.Array:
        scored = score(texts, held.value, settings.sentence_threshold)
        _bytes.give_back()
        return scored

    return docs.withColumn(name, judge(F.col("text")))


def detect(docs: DataFrame, labels: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """doc_id, p_toxic, toxic, n_sentences, offending (byte ranges and probabilities of
    the sentences that offend) for every row of ``docs``.

    Null and empty texts: p 0, not toxic.  Repeated rows are judged each.  Other
    columns are ignored.  No labels of both classes: nothing is toxic.
    """
    judged = _scored(docs.select("doc_id", "text"), train(docs, labels, settings), settings, "j")
    return judged.select(
        "doc_id",
        F.col("j.p").alias("p_toxic"),
        (F.col("j.p") >= settings.bag_threshold).alias("toxic"),
        F.col("j.sentences").alias("n_sentences"),
        F.col("j.offending").alias("offending"),
    )


def keep_clean(docs: DataFrame, labels: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """The rows of ``docs`` that are not toxic, with all their columns."""
    name = _store.fresh(docs.columns, "judged")
    judged = _scored(docs, train(docs, labels, settings), settings, name)
    return judged.where(F.col(f"{name}.p") < settings.bag_threshold).select(*[F.col(f"`{c}`") for c in docs.columns])


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return detect(_store.table(spark, sf_dir, "documents"), _store.table(spark, sf_dir, "labels"))
