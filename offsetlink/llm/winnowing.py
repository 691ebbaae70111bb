"""Benchmark decontamination by winnowing, with DataFrame functions only.

The fingerprints of a word sequence are the least k-gram hashes of all windows of w consecutive k-grams.  Any shared
run of k + w - 1 words shares a fingerprint.  Where a document shares fingerprints, the spans of k + w - 1 words around
matching k-grams are compared with those of the benchmark, word by word, so hashes only propose and words decide.
Overlapping spans that match make up the whole extent of a hit.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from offsetlink.llm import common

SPAN_WORDS, GRAM = 13, 7
# Fixed value of the contract: what separates words.
BETWEEN = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Up to so many benchmark fingerprints are looked up as constants within a document's row; more are joined.
INLINE_PRINTS = 20_000


def word_list(text: Column) -> Column:
    """Words of the contract: A-Z in lower case, then runs of digits, letters and characters beyond ASCII; null has none."""
    text = F.coalesce(text, F.lit(""))
    # Without characters beyond ASCII, lower() does the same and faster.
    lowered = F.when(F.length(text) == F.octet_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))
    return F.array_remove(F.split(lowered, BETWEEN), "")


def _span(first: Column | int, last: Column) -> Column:
    """first..last, empty if last lies before first."""
    first = F.lit(first) if isinstance(first, int) else first
    return F.when(last >= first, F.sequence(first, last)).otherwise(F.expr("cast(array() as array<int>)"))


def gram_hashes(words: Column, k: int) -> Column:
    return F.transform(_span(0, F.size(words) - k), lambda i: F.xxhash64(F.slice(words, i + 1, k)))


def winnow(hashes: Column, w: int) -> Column:
    """Distinct least hashes of all full windows of w."""
    return F.array_distinct(F.transform(_span(0, F.size(hashes) - w), lambda i: F.array_min(F.slice(hashes, i + 1, w))))


def _items(benchmark: DataFrame) -> DataFrame:
    return benchmark.select("item_id", word_list(F.col("text")).alias("words")).where(F.size("words") > 0)


def benchmark_prints(benchmark: DataFrame, span: int, k: int) -> DataFrame:
    """Different fingerprints: n (words under the hash) and print.

    Of items with span words or more, k-grams by winnowing; of shorter ones, but not empty ones, the hash of all words.
    """
    items = _items(benchmark)
    by_window = items.where(F.size("words") >= span).select(F.lit(k).alias("n"), F.explode(winnow(gram_hashes(F.col("words"), k), span - k + 1)).alias("print"))
    # Their own n goes below 0 where it could be taken for that of a k-gram.
    whole = items.where(F.size("words") < span).select((-F.size("words")).alias("n"), F.xxhash64("words").alias("print"))
    return by_window.unionByName(whole).distinct()


def benchmark_windows(benchmark: DataFrame, span: int) -> DataFrame:
    """window (span words, or all words of a shorter item, joined by spaces) and item_id, each pair once."""
    n = F.least(F.size("words"), F.lit(span))
    windows = F.transform(_span(0, F.size("words") - n), lambda i: F.array_join(F.slice("words", i + 1, n), " "))
    return _items(benchmark).select("item_id", F.explode(F.array_distinct(windows)).alias("window")).distinct()


def _empty(kind: str) -> Column:
    return F.expr(f"cast(array() as array<{kind}>)")


def _places(n: int, wanted: list[int]) -> Column:
    """Positions of grams of n words whose hash is wanted."""
    return F.filter(_span(0, F.size("words") - n), lambda i: F.xxhash64(F.slice("words", i + 1, n)).isin(wanted)) if wanted else _empty("int")


def _any(hashes: Column, wanted: list[int]) -> Column:
    return F.exists(hashes, lambda h: h.isin(wanted)) if wanted else F.lit(False)


def _with(n: int, positions: Column) -> Column:
    return F.transform(positions, lambda p: F.struct(F.lit(n).alias("n"), p.alias("p")))


def _prints(n: int, hashes: Column) -> Column:
    return F.transform(hashes, lambda h: F.struct(F.lit(n).alias("n"), h.alias("print")))


def _grams(n: int) -> Column:
    return F.transform(gram_hashes(F.col("words"), abs(n)), lambda h, p: F.struct(F.lit(n).alias("n"), p.alias("p"), h.alias("print")))


def _candidates(rows: DataFrame, ids: list[str], prints: DataFrame, span: int, k: int, inline: int) -> tuple[DataFrame, DataFrame]:
    """All rows (row_id, ids, n_words), and those that share a print: row_id, words, near (of k-grams), whole (n, p)."""
    lengths = sorted(-r.n for r in prints.where("n < 0").select("n").distinct().collect())  # fewer than span
    rows = rows.withColumn("hashes", gram_hashes(F.col("words"), k))
    kinds = [(k, winnow(F.col("hashes"), span - k + 1)), *((-n, F.array_distinct(gram_hashes(F.col("words"), n))) for n in lengths)]
    some = prints.limit(inline + 1).collect()
    if len(some) <= inline:
        wanted = {n: [r.print for r in some if r.n == n] for n, _ in kinds}
        hit = reduce(Column.__or__, (_any(hashes, wanted[n]) for n, hashes in kinds))
        # Written once, so all that follows sees the same row ids; words only of rows that share a print.
        all_rows = common.cut(rows.select(F.monotonically_increasing_id().alias("row_id"), *ids, F.size("words").alias("n_words"), F.when(hit, F.col("words")).alias("words")), "winnowed")
        whole = F.concat(_empty("struct<n:int,p:int>"), *(_with(n, _places(n, wanted[-n])) for n in lengths))
        return all_rows.drop("words"), all_rows.where("words is not null").select("row_id", "words", _places(k, wanted[k]).alias("near"), whole.alias("whole"))
    # Too many to be constants: join, then bring the words of matching documents only.
    marks = F.array_distinct(F.concat(*(_prints(n, hashes) for n, hashes in kinds)))
    all_rows = common.cut(rows.select(F.monotonically_increasing_id().alias("row_id"), *ids, F.size("words").alias("n_words"), "words", marks.alias("marks")), "winnowed")
    sharing = all_rows.select("row_id", F.explode("marks").alias("mark")).select("row_id", "mark.*").join(prints, ["n", "print"], "left_semi").select("row_id").distinct()
    matched = common.cut(all_rows.select("row_id", "words").join(sharing, "row_id", "left_semi"), "matched")
    spots = matched.select("row_id", F.explode(F.concat(*(_grams(n) for n, _ in kinds))).alias("gram")).select("row_id", "gram.*").join(prints, ["n", "print"], "left_semi")
    whole = F.struct((-F.col("n")).alias("n"), "p")
    spots = spots.groupBy("row_id").agg(F.collect_list(F.when(F.col("n") > 0, F.col("p"))).alias("near"), F.collect_list(F.when(F.col("n") < 0, whole)).alias("whole"))
    return all_rows.select("row_id", *ids, "n_words"), matched.join(spots, "row_id")


def _found(documents: DataFrame, ids: list[str], benchmark: DataFrame, span: int, k: int, inline: int) -> DataFrame:
    """ids, n_words, n_hit and items of each row of documents."""
    prints, windows = common.cut(benchmark_prints(benchmark, span, k), "prints"), common.cut(benchmark_windows(benchmark, span), "windows")
    rows = documents.select(*ids, word_list(F.col("text")).alias("words"))
    all_rows, matched = _candidates(rows, ids, prints, span, k, inline)
    # Spans of span words that hold a matching k-gram: they start up to span - k words before it.
    starts = F.array_distinct(F.flatten(F.transform("near", lambda p: _span(F.greatest(p - (span - k), F.lit(0)), F.least(p, F.size("words") - span)))))
    spots = F.concat(F.transform(starts, lambda p: F.struct(F.lit(span).alias("n"), p.alias("p"))), F.col("whole"))
    texts = F.transform(spots, lambda s: F.struct(s["n"].alias("n"), s["p"].alias("p"), F.array_join(F.slice("words", s["p"] + 1, s["n"]), " ").alias("window")))
    asked = matched.select("row_id", F.explode(texts).alias("spot")).select("row_id", "spot.*")
    # windows is a table of known size, so Spark itself decides whether to broadcast it.
    hits = common.cut(asked.join(windows.select("window").distinct(), "window", "left_semi"), "hits")
    ordered = F.array_sort(F.collect_set(F.struct("p", (F.col("p") + F.col("n")).alias("e"))))
    start = F.struct(F.lit(0).alias("end"), F.lit(0).cast("long").alias("n"))
    merged = F.aggregate("spots", start, lambda a, s: F.struct(F.greatest(a["end"], s["e"]).alias("end"), (a["n"] + F.greatest(s["e"] - F.greatest(a["end"], s["p"]), F.lit(0))).alias("n")))
    covered = hits.groupBy("row_id").agg(ordered.alias("spots")).select("row_id", merged["n"].alias("n_hit"))
    named = hits.select("row_id", "window").distinct().join(windows, "window").select("row_id", F.col("item_id").cast("string").alias("item")).where("item is not null")
    items = named.groupBy("row_id").agg(F.array_sort(F.collect_set("item")).alias("items"))
    return all_rows.join(covered, "row_id", "left").join(items, "row_id", "left").select(*ids, F.col("n_words").cast("long").alias("n_words"), F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"), F.coalesce("items", _empty("string")).alias("items"))


def contamination(documents: DataFrame, benchmark: DataFrame, span: int = SPAN_WORDS, k: int = GRAM, inline: int = INLINE_PRINTS, share: int = 20) -> DataFrame:
    """One row per document row: n_words, n_hit, items (sorted text ids), contaminated.

    A word is hit if it lies in an occurrence of span consecutive words of an item, or of a whole item of fewer.
    Contaminated: share * n_hit >= n_words > 0 hits.  Null and empty texts have no words and no hits; items with null
    or empty text are no items; an item with a null id hits words and is counted nowhere.  Repeated rows are judged
    each.  Other columns are ignored.
    """
    return _judged(documents, ["doc_id"], benchmark, span, k, inline, share)


def _judged(documents: DataFrame, ids: list[str], benchmark: DataFrame, span: int, k: int, inline: int, share: int) -> DataFrame:
    judged = _found(documents, ids, benchmark, span, k, inline)
    return judged.withColumn("contaminated", (F.col("n_hit") > 0) & (share * F.col("n_hit") >= F.col("n_words")))


def clean(documents: DataFrame, benchmark: DataFrame, span: int = SPAN_WORDS, k: int = GRAM, inline: int = INLINE_PRINTS, share: int = 20) -> DataFrame:
    """The input without contaminated rows.

    A row goes by its own text, whatever its doc_id: of rows that repeat an id, or have none, the others stay.  Rows with
    null or empty text stay.  A column named th is replaced.
    """
    rows = documents.withColumn("th", F.xxhash64("text"))
    marked = _judged(rows, ["th"], benchmark, span, k, inline, share).where("contaminated").select(F.col("th").alias("its_th")).distinct()
    return rows.join(marked, F.col("th") == F.col("its_th"), "left_anti").select(documents.columns)


def op9_winnowing(spark, sf_dir: str) -> DataFrame:
    judged = contamination(common.read(spark, sf_dir, "documents"), common.read(spark, sf_dir, "benchmark"))
    return judged.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), "contaminated")


ORACLE_OP9 = r"""
WITH w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents),
b AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark),
bw AS (
  SELECT DISTINCT item_id, least(len(ws), 13) AS n, array_to_string(ws[i:i + least(len(ws), 13) - 1], ' ') AS g
  FROM (SELECT item_id, ws, unnest(range(1, greatest(len(ws) - 12, 1) + 1)) AS i FROM b WHERE len(ws) > 0)),
ns AS (SELECT DISTINCT n FROM bw),
dw AS (
  SELECT doc_id, n, i, array_to_string(ws[i:i + n - 1], ' ') AS g
  FROM (SELECT doc_id, ws, n, unnest(range(1, len(ws) - n + 2)) AS i FROM w, ns WHERE len(ws) >= n)),
hit AS (SELECT dw.doc_id, dw.i, dw.n, bw.item_id FROM dw JOIN bw ON dw.g = bw.g AND dw.n = bw.n),
c AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM hit) GROUP BY doc_id),
it AS (SELECT doc_id, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS ids FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS s FROM hit) GROUP BY doc_id)
SELECT w.doc_id, CAST(len(w.ws) AS BIGINT) AS n_words, CAST(coalesce(c.n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(it.n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(it.ids, '')) AS items_sha256, coalesce(c.n_hit, 0) > 0 AND 20 * coalesce(c.n_hit, 0) >= len(w.ws) AS contaminated
FROM w LEFT JOIN c USING (doc_id) LEFT JOIN it USING (doc_id)"""
