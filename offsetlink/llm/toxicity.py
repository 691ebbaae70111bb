"""Toxicity by multiple-instance learning: sentences are scored, documents are labelled.

A sentence is toxic with probability sigmoid(bias + weights of its words); a document is toxic if any sentence is, so
its probability is the noisy-or of its sentences.  Bias and weights, of either sign, maximise the likelihood of document
labels less a weighted l1 penalty: a feature's penalty is SCREEN standard deviations of its gradient where it has no
effect.  So most weights are 0, the model is a short lexicon, and a sentence's words explain its score.
"""

from __future__ import annotations

import math
import re
from array import array
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from offsetlink.llm import common

#: The model is fitted on so many labelled documents at most, those with the least hashes, whole ones.
SAMPLE_DOCS = 6000
SUPPORT = 0.004  # a weight above (below) 0 needs this share of the sample's positive documents with (others) its feature, and five at least
SCREEN, RATE = 5.0, 0.05
PASSES, ROUNDS = 4, 120
MOST_WORDS = 200_000  # kept with their features between texts
PREFIXES = (4, 5)
THRESHOLD = 0.7
SENTENCE, WORD = re.compile(r"[^.!?\n|]+"), re.compile(r"[^\W\d_]+")
SCORED = "doc_id {0}, score double, sentences array<struct<start:long,end:long,score:double>>"


def _sigmoid(x):
    return 1 / (1 + np.exp(-x))


def features(word: str) -> list[str]:
    """A word, and its beginnings of four and five letters (marked by a dash), which inflected words share."""
    return [word, *(f"{word[:n]}-" for n in PREFIXES if len(word) > n)]


class Lexicon:
    """Bias and weights of the sentence model."""

    def __init__(self, bias: float, weights: dict[str, float]) -> None:
        self.bias, self.weights = bias, weights
        self.quiet = math.log1p(-float(_sigmoid(bias)))
        self.known: dict[str, list[str]] = {}

    def _of(self, words: set[str]) -> set[str]:
        """Features with a weight among those of the words."""
        if len(self.known) > MOST_WORDS:
            self.known.clear()
        for w in words.difference(self.known):
            self.known[w] = [f for f in features(w) if f in self.weights]
        return set(chain.from_iterable(map(self.known.__getitem__, words)))

    def score(self, text: str | None) -> tuple[float, list[tuple[int, int, float]]]:
        """Probability of a text, and the sentences with any word of the lexicon; positions are code points."""
        text = text or ""
        lowered = text.lower()
        if len(lowered) != len(text):
            lowered = "".join(x if len(x := c.lower()) == 1 else c for c in text)
        if not self._of(set(WORD.findall(lowered))):
            return -math.expm1(self.quiet * max(sum(1 for _ in SENTENCE.finditer(lowered)), 1)), []
        found, log_clean = [], 0.0
        for m in SENTENCE.finditer(lowered):
            if known := self._of(set(WORD.findall(m[0]))):
                p = float(_sigmoid(self.bias + math.fsum(self.weights[f] for f in known)))
                found.append((m.start(), m.end(), p))
                log_clean += math.log1p(-min(p, 1 - 1e-12))
            else:
                log_clean += self.quiet
        return -math.expm1(log_clean), found


def _different(a: np.ndarray, b: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """The different pairs of two arrays, the second of numbers below n."""
    pairs = np.unique(a.astype(np.int64) * max(n, 1) + b)
    return (pairs // max(n, 1)).astype(np.int32), (pairs % max(n, 1)).astype(np.int32)


class Bags:
    """Sentences of documents as sets of features: parallel arrays of sentence and feature, and each sentence's document.

    Features are those of support documents at least of either label.  Words are kept as small numbers and taken apart into
    features one kind at a time, so that whole texts of the sample fit a driver.
    """

    def __init__(self, texts: list[str], y: np.ndarray, support: list[float]) -> None:
        known: dict[str, int] = {}
        words, sentences, owners = array("i"), array("i"), array("i")
        for i, text in enumerate(texts):
            for sentence in SENTENCE.findall(text.lower()) or [""]:
                ids = {known.setdefault(w, len(known)) for w in WORD.findall(sentence)}
                words.extend(ids)
                sentences.extend([len(owners)] * len(ids))
                owners.append(i)
        self.doc = np.frombuffer(owners, np.int32)
        words, sentences = np.frombuffer(words, np.int32), np.frombuffer(sentences, np.int32)
        vocabulary = list(known)
        del known
        self.names, rows, cols, up, down = [], [], [], [], []
        for kind in range(1 + len(PREFIXES)):
            ids: dict[str, int] = {}
            if kind:
                n = PREFIXES[kind - 1]
                of_word = np.array([ids.setdefault(w[:n], len(ids)) if len(w) > n else -1 for w in vocabulary], np.int32)
                names = list(ids)
            else:
                of_word, names = np.arange(len(vocabulary), dtype=np.int32), vocabulary
            feature = of_word[words]
            has = feature >= 0
            d, f = _different(self.doc[sentences[has]], feature[has], len(names))
            with_label = np.bincount(f, y[d], len(names))
            without = np.bincount(f, 1 - y[d], len(names))
            some = np.flatnonzero((with_label >= support[0]) | (without >= support[1]))
            place = np.full(len(names) + 1, -1, np.int32)
            place[some] = np.arange(len(some)) + len(self.names)
            feature = place[feature]
            has = feature >= 0
            r, c = _different(sentences[has], feature[has], len(self.names) + len(some))
            rows.append(r)
            cols.append(c)
            up.append(with_label[some] >= support[0])
            down.append(without[some] >= support[1])
            self.names += [f"{names[i]}-" if kind else names[i] for i in some.tolist()]
        self.rows, self.cols, self.up, self.down = map(np.concatenate, (rows, cols, up, down))

    def by_feature(self, of_sentence: np.ndarray) -> np.ndarray:
        """Sums over each feature's sentences."""
        out = np.zeros(len(self.names))
        for at in range(0, len(self.rows), 1 << 20):
            out += np.bincount(self.cols[at : at + (1 << 20)], of_sentence[self.rows[at : at + (1 << 20)]], len(out))
        return out


def train(texts: list[str], labels: list[int], screen: float = SCREEN, passes: int = PASSES, rounds: int = ROUNDS) -> Lexicon:
    """Proximal gradient ascent on the noisy-or likelihood, on sentences as bags of features.

    Each pass takes into the working set all features whose gradient exceeds their penalty, which is the condition that
    a weight of 0 is not optimal, and then fits bias and working set.
    """
    y = np.array(labels, float)
    if not y.any() or y.all():
        return Lexicon(12.0 if len(y) and y.all() else -12.0, {})
    bags = Bags(texts, y, [max(5, SUPPORT * y.sum()), max(5, SUPPORT * (1 - y).sum())])
    doc, up, down, n = bags.doc, bags.up, bags.down, len(bags.names)

    def pulls(logits):
        """d log likelihood / d logit of a sentence: its share of a positive document, or minus its own probability."""
        p = np.clip(_sigmoid(logits), 1e-12, 1 - 1e-9)
        clean = np.bincount(doc, np.log1p(-p), len(y))
        dirty = np.maximum(-np.expm1(clean), 1e-12)
        return p, clean, dirty, np.where(y[doc] > 0, p * np.exp(clean)[doc] / dirty[doc], -p)

    bias, w, working, penalty = -math.log(len(doc) / y.sum()), np.zeros(n), np.zeros(0, np.int64), None
    r, c = np.zeros(0, np.int32), np.zeros(0, np.int32)
    for _ in range(passes):
        p, clean, dirty, pull = pulls(bias + np.bincount(r, w[working][c], len(doc)))
        gradient = bags.by_feature(pull)
        if penalty is None:
            # Variance of a sentence's pull where labels are drawn with the model's own probabilities.
            spread = dirty[doc] * (p * np.exp(clean)[doc] / dirty[doc]) ** 2 + (1 - dirty[doc]) * p**2
            penalty = screen * np.sqrt(bags.by_feature(spread))
        more = np.flatnonzero((w == 0) & (up & (gradient > penalty) | down & (gradient < -penalty)))
        fresh = np.setdiff1d(more, working)
        if not len(fresh) and len(working):
            break
        working = np.union1d(working, fresh)
        place = np.full(n, -1)
        place[working] = np.arange(len(working))
        ok = place[bags.cols] >= 0
        r, c, v, cost = bags.rows[ok], place[bags.cols[ok]], w[working], penalty[working]
        low, high = np.where(down[working], -np.inf, 0), np.where(up[working], np.inf, 0)
        mean, square, mean_bias, square_bias = np.zeros(len(v)), np.zeros(len(v)), 0.0, 0.0
        for step in range(1, rounds + 1):
            pull = pulls(bias + np.bincount(r, v[c], len(doc)))[3]
            slope, of_bias = np.bincount(c, pull[r], len(v)), float(pull.sum())
            # At 0 the penalty takes from the gradient what it can; elsewhere it pulls towards 0.
            slope = np.where(v == 0, np.sign(slope) * np.maximum(np.abs(slope) - cost, 0), slope - cost * np.sign(v))
            # Steps of momentum over the root of the mean square; a weight that would change its sign stops at 0.
            mean, square = mean + 0.1 * (slope - mean), square + 0.01 * (slope**2 - square)
            mean_bias, square_bias = mean_bias + 0.1 * (of_bias - mean_bias), square_bias + 0.01 * (of_bias**2 - square_bias)
            one, two = 1 - 0.9**step, 1 - 0.99**step
            new = np.clip(v + RATE * (mean / one) / (np.sqrt(square / two) + 1e-6), low, high)
            v = np.where(new * v < 0, 0, new)
            bias += RATE * (mean_bias / one) / (math.sqrt(square_bias / two) + 1e-6)
        w[working] = v
    # A weight that goes back and forth around 0 is at most a step or two away from it.
    return Lexicon(float(bias), {f: float(w[i]) for i, f in enumerate(bags.names) if abs(w[i]) > 2 * RATE})


def fit(documents: DataFrame, labels: DataFrame, sample_docs: int = SAMPLE_DOCS) -> Lexicon:
    """Learn from labelled documents (labels: doc_id, toxic).

    The sample is bounded: the sample_docs labelled ids with the least hashes, as whole texts; of rows that repeat an id,
    the one with the least text.  Null labels, ids and texts are left out; an id labelled more than once counts with its
    greatest label.
    """
    chosen = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_docs)
    rows = documents.where(F.col("text").isNotNull()).select("doc_id", "text")
    found = rows.join(F.broadcast(chosen), "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"), F.max("toxic").alias("toxic")).collect()
    found.sort(key=lambda r: (r.doc_id, r.text))
    unique = list({(r.text, r.toxic): r for r in found}.values())  # copies don't count as more evidence
    return train([r.text for r in unique], [int(r.toxic) for r in unique])


def _scored(batches, bias: float, weights: dict[str, float]):
    lexicon = Lexicon(bias, weights)
    for b in batches:
        done = [lexicon.score(t) for t in b.column("text").to_pylist()]
        spans = pa.array([[{"start": s, "end": e, "score": p} for s, e, p in d[1]] for d in done], pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())])))
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([d[0] for d in done], pa.float64()), spans], names=["doc_id", "score", "sentences"])


def score(documents: DataFrame, lexicon: Lexicon) -> DataFrame:
    """doc_id, score and sentences (start, end in code points, score) with words of the lexicon, of each whole text.

    Narrow.  Null and empty texts count as one sentence without known words.  Repeated rows are scored each; other
    columns are ignored.
    """
    common.bound_batches(documents.sparkSession)
    kind = documents.schema["doc_id"].dataType.simpleString()
    return documents.select("doc_id", "text").mapInArrow(lambda batches: _scored(batches, lexicon.bias, lexicon.weights), SCORED.format(kind))


def op8_toxicity(spark, sf_dir: str) -> DataFrame:
    documents, labels = common.read(spark, sf_dir, "documents"), common.read(spark, sf_dir, "labels")
    held_out = common.fold(F.col("doc_id"), 3) == 1
    lexicon = fit(documents, labels.select("doc_id", "toxic").where(~held_out))
    scored = score(documents, lexicon)
    return scored.select("doc_id", F.coalesce(held_out, F.lit(False)).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
