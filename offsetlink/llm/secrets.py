"""Secret scans with DataFrame functions only: fixed patterns, and sliding-window entropy over candidate strings.

Positions come from splitting a text at a pattern: the pieces and the matches alternate, so their lengths add up to the
offsets.  The entropy of a window of w symbols with counts n is log2(w) - sum(n log2 n) / w; moving the window by one
symbol changes two counts and two terms of the sum.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from offsetlink.llm import common

# Fixed values of the contract, in its order.
KINDS = {
    "assign": r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""",
    "access": r"AKIA[A-Z0-9]{14,}",
    "hex": r"[0-9a-f]{16,}",
}
ASSIGN_LEAST = 12

CANDIDATE = r"(?<![A-Za-z0-9+/=_-])[A-Za-z0-9+/=_-]{20,}+"
SYMBOLS = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/=_-"
WINDOW = 20
#: Character class, its pattern, and the bits a symbol that some window needs at least.
CLASSES = (("hex", r"^[0-9a-fA-F]+$", 2.9), ("alnum", r"^[A-Za-z0-9]+$", 3.7), ("base64", r"", 3.8))
#: Strings that look random and aren't secret: placeholders, counting sequences, paths of words.
ALLOW = (r"(?i)example|sample|placeholder|dummy|changeme|redacted", r"0123456789|abcdefgh|ABCDEFGH|(.)\1{5}", r"^/?(?:[A-Za-z]+[/_-])+[A-Za-z]*\d{0,4}$")
SPAN = "array<struct<start:int,rank:int,end:int,kind:string>>"
MASK = "[SECRET]"


def _bound(value: Column, use) -> Column:
    """use(value), with value computed once: a lambda would compute a column expression for each element again."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def _located(text: Column, pattern: str, kind: str, rank: int, keep=None, group: int = 0) -> Column:
    """Spans of a pattern's matches; keep(group's text) says which of them count."""
    # One piece more than matches: the last entry of the zip has no match.
    parts = {"piece": F.split(text, pattern, -1), "hit": F.regexp_extract_all(text, F.lit(pattern), F.lit(0))}
    if group:
        parts["value"] = F.regexp_extract_all(text, F.lit(pattern), F.lit(group))
    value = "value" if group else "hit"

    def step(acc: Column, part: Column) -> Column:
        start = acc["at"] + F.length(part["piece"])
        end = start + F.length(part["hit"])
        span = F.array(F.struct(start.alias("start"), F.lit(rank).alias("rank"), end.alias("end"), F.lit(kind).alias("kind")))
        found = F.concat(acc["spans"], span)
        spans = F.when(keep(part[value]), found).otherwise(acc["spans"]) if keep else found
        return F.when(part["hit"].isNull(), acc).otherwise(F.struct(end.alias("at"), spans.alias("spans")))

    none = F.expr(f"cast(array() as {SPAN})")
    zipped = F.arrays_zip(*(c.alias(n) for n, c in parts.items()))
    total = F.aggregate(zipped, F.struct(F.lit(0).alias("at"), none.alias("spans")), step)
    return F.when(text.rlike(pattern), total["spans"]).otherwise(none)


def _n_log_n(n: Column) -> Column:
    return F.when(n > 1, n * F.log2(n.cast("double"))).otherwise(F.lit(0.0))


def _peak_entropy(text: Column, window: int) -> Column:
    """The largest entropy of a full window of the string, by counts that change with what enters and leaves."""
    codes = F.transform(F.split(text, ""), lambda c: F.instr(F.lit(SYMBOLS), c) - 1)
    return _bound(codes, lambda known: _peak(known, window))


def _peak(codes: Column, window: int) -> Column:
    start = F.struct(F.array_repeat(F.lit(0), len(SYMBOLS)).alias("n"), F.lit(0.0).alias("s"), F.lit(0.0).alias("best"))

    def moved(acc: Column, code: Column, by: int) -> tuple[Column, Column]:
        old = F.get(acc["n"], code)
        return F.transform(acc["n"], lambda n, k: F.when(k == code, n + by).otherwise(n)), acc["s"] + _n_log_n(old + by) - _n_log_n(old)

    def enter(acc: Column, i: Column) -> Column:
        n, s = moved(acc, F.get(codes, i), 1)
        return F.struct(n.alias("n"), s.alias("s"), acc["best"].alias("best"))

    def leave(acc: Column, i: Column) -> Column:
        n, s = moved(acc, F.get(codes, i - window), -1)
        return F.when(i >= window, F.struct(n.alias("n"), s.alias("s"), acc["best"].alias("best"))).otherwise(acc)

    def judge(acc: Column, i: Column) -> Column:
        bits = F.lit(math.log2(window)) - acc["s"] / window
        return F.struct(acc["n"].alias("n"), acc["s"].alias("s"), F.when(i >= window - 1, F.greatest(acc["best"], bits)).otherwise(acc["best"]).alias("best"))

    # Three small steps for each position, each with the state of the one before.
    steps = F.sequence(F.lit(0), 3 * F.size(codes) - 1)

    def step(acc: Column, j: Column) -> Column:
        i = F.floor(j / 3).cast("int")
        return F.when(j % 3 == 0, leave(acc, i)).when(j % 3 == 1, enter(acc, i)).otherwise(judge(acc, i))

    return F.aggregate(steps, start, step)["best"]


def _random_looking(allow: tuple[str, ...], window: int):
    def keep(hit: Column) -> Column:
        mixed = hit.rlike("[0-9]") & hit.rlike("[A-Za-z]")
        for pattern in allow:
            mixed = mixed & ~hit.rlike(pattern)
        least = F.lit(CLASSES[-1][2])
        for _, pattern, bits in reversed(CLASSES[:-1]):
            least = F.when(hit.rlike(pattern), F.lit(bits)).otherwise(least)
        return F.when(mixed, _peak_entropy(hit, window) >= least).otherwise(F.lit(False))

    return keep


def scan(documents: DataFrame, allow: tuple[str, ...] = ALLOW, window: int = WINDOW) -> DataFrame:
    """The input with columns base_spans and entropy_spans (arrays of start, rank, end, kind; code points, end exclusive).

    Base spans are the contract's; the allow-list never suppresses them.  An entropy span is a candidate string that
    mixes letters and digits, matches nothing of the allow-list, has a window over its class's threshold, and meets no
    base span.  Null and empty text have no spans; repeated rows are scanned each.  Columns with these two names are
    replaced; all others stay.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    how = {"assign": {"keep": lambda value: F.length(value) >= ASSIGN_LEAST, "group": 2}}
    base = [_located(text, p, kind, rank, **how.get(kind, {})) for rank, (kind, p) in enumerate(KINDS.items())]
    free = lambda e: ~F.exists("base_spans", lambda b: (b["start"] < e["end"]) & (e["start"] < b["end"]))
    drawn = _located(text, CANDIDATE, "entropy", len(KINDS), _random_looking(allow, window))
    return documents.withColumn("base_spans", F.array_sort(F.concat(*base))).withColumn("entropy_spans", drawn).withColumn("entropy_spans", F.filter("entropy_spans", free))


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def report(scanned: DataFrame) -> DataFrame:
    """Counts, digest and list of spans for each row."""
    count = lambda kind: F.size(F.filter("base_spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    every = F.array_sort(F.concat("base_spans", "entropy_spans"))
    return scanned.select("doc_id", *map(count, KINDS), F.sha2(_joined(F.col("base_spans")), 256).alias("base_sha256"), _joined(every).alias("spans"))


def redact(scanned: DataFrame, mask: str = MASK) -> DataFrame:
    """text with every span replaced; overlapping spans become one mask.  Null text stays null."""
    start = F.struct(F.lit("").alias("out"), F.lit(0).alias("at"))

    def step(acc: Column, s: Column) -> Column:
        gap = F.substring(F.col("text"), acc["at"] + 1, s["start"] - acc["at"])
        fresh = F.struct(F.concat(acc["out"], gap, F.lit(mask)).alias("out"), s["end"].alias("at"))
        grown = F.struct(acc["out"].alias("out"), F.greatest(acc["at"], s["end"]).alias("at"))
        return F.when((acc["at"] > 0) & (s["start"] < acc["at"]), grown).otherwise(fresh)

    spans = F.array_sort(F.concat("base_spans", "entropy_spans"))
    cleaned = F.aggregate(spans, start, step, lambda acc: F.concat(acc["out"], F.substr(F.col("text"), acc["at"] + 1)))
    return scanned.withColumn("text", F.when(F.size(spans) > 0, cleaned).otherwise(F.col("text"))).drop("base_spans", "entropy_spans")


def op5_secrets(spark, sf_dir: str) -> DataFrame:
    return report(scan(common.read(spark, sf_dir, "documents").select("doc_id", "text")))


def secrets_base(spark, sf_dir: str) -> DataFrame:
    """The base columns of op5_secrets alone, which SQL expresses too."""
    return op5_secrets(spark, sf_dir).drop("spans")


def _spans_sql(pattern: str, kind: str, rank: int, group: int, least: int) -> str:
    hits = f"regexp_extract_all(t, '{pattern}')"
    values = f"regexp_extract_all(t, '{pattern}', {group})"
    return f"""SELECT doc_id, {rank} AS rank, '{kind}' AS kind, list_sum(list_transform(parts[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(hits[1:i - 1], lambda x: length(x))), 0) AS a, length(hits[i]) AS n
  FROM (SELECT doc_id, string_split_regex(t, '{pattern}') AS parts, {hits} AS hits, {values} AS vals, unnest(range(1, len({hits}) + 1)) AS i FROM d) WHERE length(vals[i]) >= {least}"""


ORACLE_BASE = f"""
WITH d AS MATERIALIZED (SELECT doc_id, coalesce(text, '') AS t FROM documents),
s AS MATERIALIZED (
  {_spans_sql(KINDS["assign"].replace("'", "''"), "assign", 0, 2, ASSIGN_LEAST)}
  UNION ALL {_spans_sql(KINDS["access"], "access", 1, 0, 18)}
  UNION ALL {_spans_sql(KINDS["hex"], "hex", 2, 0, 16)})
SELECT d.doc_id, count(*) FILTER (WHERE kind = 'assign') AS n_assign, count(*) FILTER (WHERE kind = 'access') AS n_access, count(*) FILTER (WHERE kind = 'hex') AS n_hex,
  sha256(coalesce(string_agg(kind || ':' || CAST(a AS BIGINT) || ':' || CAST(a + n AS BIGINT), ',' ORDER BY a, rank), '')) AS base_sha256
FROM d LEFT JOIN s USING (doc_id) GROUP BY d.doc_id"""
