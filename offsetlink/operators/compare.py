"""Candidate documents compared where they meet: what a comparison needs of a document goes once to each of its blocks.

Sent to each pair instead, texts would take the shuffle as many times as a record has candidates.  A document is packed as
its distinct words, and as a bit map of its word triples, which bounds from above how many triples two documents share.
Only pairs that the bound leaves open are compared triple by triple, from their texts.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from offsetlink.functions import portable
from offsetlink.operators import resolve

PACKED = "doc_id long, source int, lang string, n_chars long, n_lines long, title binary, body binary, n long, mark binary, bits binary"
COMPARED = "d1 long, d2 long, s1 int, s2 int, x1 double, x2 double, x3 double, x4 double, x5 double, near int"
#: Pairs still open that are sent to all executors, instead of texts to the pairs.
SENT = 500_000
#: Hashes of words that a task keeps at once; more take the memory that two tasks of an executor need.
HELD = 50_000
#: Lower-case letters and digits as they are, A-Z lowered, all else (bytes beyond ASCII too) a blank.
FOLDED = bytes(c if chr(c) in "abcdefghijklmnopqrstuvwxyz0123456789" else c + 32 if 65 <= c <= 90 else 32 for c in range(256))
TITLE = re.compile(r"[^.|\n]*")
FACTORS = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9], np.uint64)


class Hashes(dict):
    """64-bit hashes of words."""

    def __missing__(self, word: bytes) -> int:
        h = self[word] = int.from_bytes(hashlib.blake2b(word, digest_size=8).digest(), "little")
        return h


def words(text: str) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(FOLDED).split()


def triples(ws: list[bytes], hashes: Hashes) -> np.ndarray:
    """Distinct hashes of runs of three words, rising."""
    h = np.fromiter(map(hashes.__getitem__, ws), np.uint64, len(ws))
    a, b, c = (h[k : len(h) - 2 + k] if len(h) > 2 else h[:0] for k in range(3))
    return np.unique(a * FACTORS[0] + b * FACTORS[1] + c * FACTORS[2])


def bit_map(grams: np.ndarray) -> bytes:
    """A bit for each triple, by its low bits; the number of places is a power of two, twice the triples at least."""
    places = 1 << max(3, (2 * len(grams) - 1).bit_length())
    bits = np.zeros(places, bool)
    bits[grams & np.uint64(places - 1)] = True
    return np.packbits(bits, bitorder="little").tobytes()


def most_shared(n1: int, bits1: bytes, n2: int, bits2: bytes) -> int:
    """No two sets of n1 and n2 triples with these bit maps share more: a bit that one lacks stands for a triple it lacks."""
    a, b = int.from_bytes(bits1, "little"), int.from_bytes(bits2, "little")
    size1, size2 = 8 * len(bits1), 8 * len(bits2)
    while size1 > size2:
        size1 //= 2
        a = (a >> size1) | (a & ((1 << size1) - 1))
    while size2 > size1:
        size2 //= 2
        b = (b >> size2) | (b & ((1 << size2) - 1))
    return min(n1 - (a & ~b).bit_count(), n2 - (b & ~a).bit_count())


def _packed(batches):
    fields = [x.split() for x in PACKED.split(", ")]
    kinds = {"int": pa.int32(), "long": pa.int64(), "string": pa.string(), "binary": pa.binary()}
    hashes = Hashes()
    for batch in batches:
        if len(hashes) > HELD:
            hashes.clear()
        rows = []
        for doc_id, source, lang, n_chars, text in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            text = text or ""
            ws = words(text)
            grams = triples(ws, hashes)
            joined = lambda x: b" ".join(sorted(set(x)))
            mark = hashlib.blake2b(grams.tobytes(), digest_size=16).digest()
            rows.append((doc_id, source, lang, n_chars, text.count("\n") + 1, joined(words(TITLE.match(text).group())), joined(ws), len(grams), mark, bit_map(grams)))
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, kinds[k]) for c, (_, k) in zip(zip(*rows, strict=True), fields, strict=True)], names=[n for n, _ in fields])


def _share(a: set, b: set) -> float:
    both = len(a & b)
    union = len(a) + len(b) - both
    return both / union if union else 0.0


def _far(a: int | None, b: int | None) -> float | None:
    return None if a is None or b is None else abs(a - b) / max(a, b, 1)


def _pairs(block: list[tuple], out: list[tuple]) -> None:
    """Pairs of a block whose first shared key is the block's: no key before it is in both."""
    sets = [(frozenset(r[0]), set(r[6].split()), set(r[7].split())) for r in block]
    for i, (_, d1, s1, g1, c1, l1, _, _, n1, m1, b1) in enumerate(block):
        for j, (_, d2, s2, g2, c2, l2, _, _, n2, m2, b2) in enumerate(block):
            if not d1 < d2 or s1 is None or s2 is None or s1 == s2 or not sets[i][0].isdisjoint(sets[j][0]):
                continue
            if not n1 or not n2 or 2 * min(n1, n2) < max(n1, n2):
                near = 0
            elif m1 == m2:
                near = 1
            else:
                near = 2 if 3 * most_shared(n1, b1, n2, b2) >= n1 + n2 else 0
            same = 1.0 if g1 is not None and g1 == g2 else 0.0
            out.append((d1, d2, s1, s2, _share(sets[i][1], sets[j][1]), _share(sets[i][2], sets[j][2]), _far(c1, c2), _far(l1, l2), same, near))


def _compared(batches):
    fields = [x.split() for x in COMPARED.split(", ")]
    kinds = {"int": pa.int32(), "long": pa.int64(), "double": pa.float64()}
    key, block, out = None, [], []

    def batch() -> pa.RecordBatch:
        done = pa.RecordBatch.from_arrays([pa.array(c, kinds[k]) for c, (_, k) in zip(zip(*out, strict=True), fields, strict=True)], names=[n for n, _ in fields])
        out.clear()
        return done

    for b in batches:
        for k, *row in zip(*(c.to_pylist() for c in b.columns), strict=True):
            if k != key:
                _pairs(block, out)
                key, block = k, []
            block.append(tuple(row))
        if out:
            yield batch()
    _pairs(block, out)
    if out:
        yield batch()


def gram_hashes(text: Column) -> Column:
    """Distinct hashes of a text's runs of three words, rising."""
    ws = F.filter(F.split(portable.ascii_fold(text), "[^a-z0-9]+"), lambda w: w != "")
    # The lambda sees its own argument only: it would else compute the words for each element.
    shifted = F.arrays_zip(ws.alias("a"), F.slice(ws, 2, F.greatest(F.size(ws), F.lit(1))).alias("b"), F.slice(ws, 3, F.greatest(F.size(ws), F.lit(1))).alias("c"))
    runs = F.filter(shifted, lambda z: z["c"].isNotNull())
    return F.array_sort(F.array_distinct(F.transform(runs, lambda z: F.xxhash64(z["a"], z["b"], z["c"]))))


def linked(open_: DataFrame, documents: DataFrame) -> DataFrame:
    """Of pairs (d1, d2) those whose triples have Jaccard >= 1/2, from their texts."""
    sent = F.broadcast if open_.count() <= SENT else lambda x: x
    ids = open_.select(F.col("d1").alias("doc_id")).unionByName(open_.select(F.col("d2").alias("doc_id"))).distinct()
    texts = documents.join(sent(ids), "doc_id", "left_semi").select("doc_id", gram_hashes(F.col("text")).alias("grams"))
    side = lambda k: texts.select(F.col("doc_id").alias(f"d{k}"), F.col("grams").alias(f"grams{k}"))
    common = F.size(F.array_intersect("grams1", "grams2"))
    found = open_.join(side(1), "d1").join(side(2), "d2").where(2 * common >= F.size("grams1") + F.size("grams2") - common)
    return sent(found.select("d1", "d2", F.lit(True).alias("linked_")))


def compared(documents: DataFrame, keys: DataFrame) -> DataFrame:
    """Pairs of records of different sources that share a key (doc_id, keys: sorted structs of df and token), each once:
    d1, d2, s1, s2, shares of common title words and body words, distances of length and lines, equal language, and match
    (their triples have Jaccard >= 1/2)."""
    spark = documents.sparkSession
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "400")
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", "1m")
    source = F.regexp_extract("source", r"(\d+)$", 1).try_cast("int")
    packed = documents.select("doc_id", source.alias("source"), "lang", "n_chars", "text").mapInArrow(_packed, PACKED)
    dealt = packed.join(keys, "doc_id").select(*packed.columns, "keys", F.posexplode("keys").alias("at", "key"))
    before = F.transform(F.slice("keys", F.lit(1), F.col("at")), lambda x: x["token"])
    blocks = dealt.select(F.col("key.token").alias("block_key"), before.alias("before"), *packed.columns)
    pairs = resolve.stored(blocks.repartition("block_key").sortWithinPartitions("block_key").mapInArrow(_compared, COMPARED), "compared")
    found = linked(pairs.where("near = 2").select("d1", "d2"), documents)
    match = (F.col("near") == 1) | F.coalesce("linked_", F.lit(False))
    return pairs.join(found, ["d1", "d2"], "left").withColumn("match", match).drop("near", "linked_")
