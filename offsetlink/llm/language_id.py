"""Language identification by prediction by partial matching over bytes, with frozen statistics.

For each language a tree of contexts of up to three bytes holds how often each byte followed.  A byte unseen in a
context escapes to the next shorter one (method C: the escape counts as many as the different bytes seen), where bytes
seen in the longer context are excluded; below the empty context all remaining bytes of the 256 are equal.  Bytes are
taken as they are, every context of the sample is kept, and three spaces stand before a text.  Frozen statistics make the
cost of a byte a function of its context, so a text's exact code length is a sum over its runs of four bytes, each
different run costed once for a batch of texts.
"""

from __future__ import annotations

import pickle
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from offsetlink.llm import common

ORDER = 3
#: The classifier is fitted on so many documents of each language at most, whole ones.
SAMPLE_DOCS = 400
SLICE = 1 << 20
PAD = b" " * ORDER
LETTER = re.compile(r"[^\W\d_]")
PREDICTED = "doc_id {0}, lang_pred string, score double, bits array<double>"


def _grams(raw: bytes) -> np.ndarray:
    """Each byte with the three before it as one number; the first three bytes are context only."""
    x = np.frombuffer(raw, np.uint8).astype(np.uint32)
    return x[:-3] << np.uint32(24) | x[1:-2] << np.uint32(16) | x[2:-1] << np.uint32(8) | x[3:]


def _find(known: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Places in a sorted array, -1 where it lacks them."""
    if not len(known):
        return np.full(len(wanted), -1)
    at = np.minimum(np.searchsorted(known, wanted), len(known) - 1)
    return np.where(known[at] == wanted, at, -1)


class ContextTree:
    """Follow counts of one language: for each length of context its contexts, and its contexts with the byte behind."""

    def __init__(self, texts: list[str]) -> None:
        parts, size = [np.zeros(0, np.uint32)], 0
        tallies = []
        for t in texts:
            parts.append(_grams(PAD + t.encode("utf-8", "surrogatepass")))
            size += len(parts[-1])
            if size > 8 * SLICE:
                tallies.append(np.unique(np.concatenate(parts), return_counts=True))
                parts, size = [np.zeros(0, np.uint32)], 0
        tallies.append(np.unique(np.concatenate(parts), return_counts=True))
        grams, n = np.concatenate([g for g, _ in tallies]), np.concatenate([c for _, c in tallies])
        self.grams, self.counts, self.contexts, self.seen, self.kinds, self.carried = [], [], [], [], [], []
        for d in range(ORDER + 1):
            g, at = np.unique(grams & np.uint32((1 << 8 * (d + 1)) - 1), return_inverse=True)
            c = np.bincount(at, n, len(g))
            contexts, owner = np.unique(g >> np.uint32(8), return_inverse=True)
            self.grams.append(g)
            self.counts.append(c)
            self.contexts.append(contexts)
            self.seen.append(np.bincount(owner, c, len(contexts)))
            self.kinds.append(np.bincount(owner, minlength=len(contexts)).astype(float))
            # What the bytes seen here count in the next shorter context, where they will be excluded.
            shorter = self.counts[d - 1][_find(self.grams[d - 1], g & np.uint32((1 << 8 * d) - 1))] if d else np.zeros(len(g))
            self.carried.append(np.bincount(owner, shorter, len(contexts)))

    def bits(self, grams: np.ndarray) -> np.ndarray:
        """The cost of each gram's last byte after the three before it."""
        out, left = np.zeros(len(grams)), np.arange(len(grams))
        gone_n, gone_kinds = np.zeros(len(grams)), np.zeros(len(grams))
        for d in range(ORDER, -1, -1):
            g = grams[left]
            at = _find(self.contexts[d], (g >> np.uint32(8)) & np.uint32((1 << 8 * d) - 1))
            there = at >= 0
            place = _find(self.grams[d], g & np.uint32((1 << 8 * (d + 1)) - 1))
            hit = place >= 0
            n = np.where(there, self.seen[d][at] if len(self.seen[d]) else 0, 0) - gone_n[left]
            kinds = np.where(there, self.kinds[d][at] if len(self.kinds[d]) else 0, 0) - gone_kinds[left]
            some = left[hit]
            out[some] += np.log2((n + kinds)[hit] / self.counts[d][place[hit]])
            escape = ~hit & there & (n > 0)
            out[left[escape]] += np.log2((n + kinds)[escape] / kinds[escape])
            below = ~hit & there
            gone_n[left[below]], gone_kinds[left[below]] = self.carried[d][at[below]], self.kinds[d][at[below]]
            left = left[~hit]
        out[left] += np.log2(256 - gone_kinds[left])
        return out


class ContextTrees:
    """A tree for each language."""

    def __init__(self, texts: dict[str, list[str]]) -> None:
        self.langs = sorted(texts)
        self.trees = [ContextTree(texts[k]) for k in self.langs]

    def bits(self, texts: list[str]) -> np.ndarray:
        """Code length of each text in each language."""
        out = np.zeros((len(texts), len(self.langs)))
        pending, owners, size = [], [], 0
        for i, t in enumerate(texts):
            raw = t.encode("utf-8", "surrogatepass")
            for at in range(0, len(raw), SLICE):
                pending.append((raw[at - ORDER : at] if at else PAD) + raw[at : at + SLICE])
                owners.append(i)
                size += len(pending[-1])
                if size >= SLICE:
                    self._add(pending, owners, out)
                    pending, owners, size = [], [], 0
        self._add(pending, owners, out)
        return out

    def _add(self, parts: list[bytes], owners: list[int], out: np.ndarray) -> None:
        if not parts or not self.langs:
            return
        grams, at = np.unique(_grams(b"".join(parts)), return_inverse=True)
        ends = np.cumsum([len(p) for p in parts])
        starts = ends - [len(p) for p in parts]
        for k, tree in enumerate(self.trees):
            # Gram j ends with byte j + 3.
            sums = np.concatenate([[0.0], np.cumsum(tree.bits(grams)[at])])
            np.add.at(out[:, k], owners, sums[ends - ORDER] - sums[starts])

    def predict(self, texts: list[str | None]) -> list[tuple[str, float, list[float] | None]]:
        """Language, its share of the posterior, and all code lengths; ``und`` and 0 without text, letters or languages."""
        some = [i for i, t in enumerate(texts) if t and self.langs and LETTER.search(t)]
        out: list[tuple[str, float, list[float] | None]] = [("und", 0.0, None)] * len(texts)
        for i, b in zip(some, self.bits([texts[i] for i in some]), strict=True):
            best = int(b.argmin())
            out[i] = (self.langs[best], float(1 / np.exp2(np.maximum(b[best] - b, -1000)).sum()), b.tolist())
        return out


def fit(documents: DataFrame, sample_docs: int = SAMPLE_DOCS) -> ContextTrees:
    """Context trees of documents' text and lang.

    The sample is bounded: of each language the sample_docs distinct rows with the least hashes of doc_id and text, as
    whole texts.  Rows with null text or null lang are left out; without a column lang nothing is learned.
    """
    if "lang" not in documents.columns:
        return ContextTrees({})
    rows = documents.where(F.col("text").isNotNull() & F.col("lang").isNotNull()).select(F.col("lang").cast("string").alias("lang"), F.xxhash64("doc_id", "text").alias("h"), "text")
    # Of each language about twice as many rows as wanted have a hash below a bound set by its count; no group is sorted.
    counts = {r.lang: r["count"] for r in rows.groupBy("lang").count().collect()}
    if not counts:
        return ContextTrees({})
    bounds = [(k, int(-(1 << 63) + min(1.0, 2 * (sample_docs + 20) / n) * ((1 << 64) - 2049))) for k, n in sorted(counts.items())]
    bound = documents.sparkSession.createDataFrame(bounds, "lang string, bound long")
    some = rows.join(F.broadcast(bound), "lang").where(F.col("h") <= F.col("bound"))
    one = some.groupBy("lang", "h").agg(F.min("text").alias("text"))
    texts: dict[str, list[str]] = {}
    for r in sorted(one.collect(), key=lambda r: (r.lang, r.h)):
        if len(texts.setdefault(r.lang, [])) < sample_docs:
            texts[r.lang].append(r.text)
    return ContextTrees(texts)


def _predicted(batches, pickled: bytes):
    trees = pickle.loads(pickled)
    for b in batches:
        langs, scores, bits = zip(*trees.predict(b.column("text").to_pylist()), strict=True) if b.num_rows else ((), (), ())
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(langs, pa.string()), pa.array(scores, pa.float64()), pa.array(bits, pa.list_(pa.float64()))], names=["doc_id", "lang_pred", "score", "bits"])


def identify(documents: DataFrame, trees: ContextTrees) -> DataFrame:
    """doc_id, lang_pred, score, and bits (code lengths by sorted language) of each row, from whole texts.

    Narrow.  Null text, empty text and text without a letter are ``und`` with score 0; so is all text if no language was
    learned.  Ties go to the first language in order.  Repeated rows are judged each; other columns are ignored.
    """
    common.bound_batches(documents.sparkSession)
    shared = common.share(documents.sparkSession, trees)
    kind = documents.schema["doc_id"].dataType.simpleString()
    return documents.select("doc_id", "text").mapInArrow(lambda batches: _predicted(batches, shared.value), PREDICTED.format(kind))


def _assigned(batches, pickled: bytes):
    trees = pickle.loads(pickled)
    for b in batches:
        langs = pa.array([x[0] for x in trees.predict(b.column("text").to_pylist())], pa.string())
        at = b.schema.get_field_index("lang")
        yield b.set_column(at, "lang", langs)


def assign(documents: DataFrame, trees: ContextTrees) -> DataFrame:
    """The input with lang as predicted (added if it isn't there); all rows and other columns stay."""
    common.bound_batches(documents.sparkSession)
    shared = common.share(documents.sparkSession, trees)
    rows = documents.withColumn("lang", F.col("lang").cast("string") if "lang" in documents.columns else F.lit(None).cast("string"))
    return rows.mapInArrow(lambda batches: _assigned(batches, shared.value), rows.schema)


def training_rows(documents: DataFrame) -> DataFrame:
    return documents.where(common.fold(F.col("doc_id"), 5) != 0)


def op4_language_id(spark, sf_dir: str) -> DataFrame:
    documents = common.read(spark, sf_dir, "documents")
    found = identify(documents, fit(training_rows(documents)))
    return found.select("doc_id", F.coalesce(common.fold(F.col("doc_id"), 5) == 0, F.lit(False)).alias("held_out"), "lang_pred", "score")
