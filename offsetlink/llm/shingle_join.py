"""N-gram Jaccard join with several global token orders.

Two sets of sizes n and m with Jaccard >= t share at least ceil(t n) tokens, so their shared tokens reach into a prefix
of either set under any global order.  Orders filter twice:

Over the whole table, sets meet by tokens:
1. by hash: a set keeps its n - ceil(t n) + l least hashes, l about a tenth of n.  A partner, which may be smaller,
   shares l' = l(ceil(t n)) of them, so a set with fewer hashes that any other keeps is out; most documents end here.
2. by frequency among kept hashes, rarest first: a pair shares a token among the first m - l' + 1 of m kept ones.  Hashes
   of common passages come last and are mostly cut off.  Sets that share such tokens, directly or through others, form a
   family; a pair across families can't be similar.

Within a family, a candidate pair must share a prefix token under each of three orders (by hash, by frequency in the
group, by a second hash), and only what is in all three filters is verified by counting shared tokens.  Pairs that are
connected already aren't looked at, as only components are asked for.

Nothing is gathered by a token alone: documents are taken in flushes, a flush asks once for the frequency of each of its
tokens, and links the sets that share one before it passes on one of them.  Families are compared in blocks bounded in
sets and tokens: first each block with itself and with some leaders of the family, then only blocks of different
components.  Equal sets are one set (by a 64-bit hash of the set; shingles are 64-bit hashes too).
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from offsetlink.llm import common
from offsetlink.llm.common import mix64
from offsetlink.llm.components import components

SHINGLE = 5
#: Similarity in hundredths.
LEAST = 80
SPARE, SPARE_LEAST = 10, 12  # the longer prefix of order A has n // SPARE tokens more than needed, or so many
#: Up to so many members of families are broadcast to the scan of their texts; more are joined by a shuffle.
BROADCAST_ROWS = 400_000
PIECE = 4 << 20
FLUSH = 300_000  # kept tokens of the documents taken together
BUCKET_BYTES = 8 << 20  # of the input for each bucket of tokens
BLOCK_SETS, BLOCK_TOKENS, LEADERS = 1024, 1_500_000, 64
BASE, STEP = 0x9E3779B97F4A7C15 | 1, 0xD1342543DE82EF95
INVERSE = pow(BASE, -1, 1 << 64)
SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
U = np.uint64


def word_hashes(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Hash and start of each word of lower-cased text: differences of prefix sums of a polynomial."""
    x = np.frombuffer(raw, np.uint8)
    gap = np.concatenate([[True], SPACE[x], [True]])
    starts, ends = np.flatnonzero(gap[:-1] & ~gap[1:]), np.flatnonzero(~gap[:-1] & gap[1:])
    if not len(starts):
        return np.zeros(0, U), starts
    with np.errstate(over="ignore"):
        powers = np.full(len(x) + 1, BASE, U)
        powers[0] = 1
        np.multiply.accumulate(powers, out=powers)
        sums = np.zeros(len(x) + 1, U)
        np.cumsum((x.astype(U) + U(1)) * powers[:-1], out=sums[1:])
        back = np.full(len(x) + 1, INVERSE, U)
        back[0] = 1
        np.multiply.accumulate(back, out=back)
        return mix64((sums[ends] - sums[starts]) * back[starts] + (ends - starts).astype(U)), starts


def combined(words: np.ndarray, n: int) -> np.ndarray:
    """Hashes of all runs of n words."""
    if len(words) < n:
        return np.zeros(0, U)
    with np.errstate(over="ignore"):
        h = np.full(len(words) - n + 1, n, U)
        for k in range(n):
            h = h * U(STEP) + words[k : len(words) - n + 1 + k]
        return mix64(h)


def _whole(raw: bytes, n: int) -> np.ndarray:
    """Distinct shingle hashes of one text, in pieces that end between words."""
    carry, found, at, total = np.zeros(0, U), [], 0, 0
    while at < len(raw):
        end = at + PIECE
        while end < len(raw) and not SPACE[raw[end]]:
            end += 1
        words = np.concatenate([carry, word_hashes(raw[at:end])[0]])
        total += len(words) - len(carry)
        found.append(np.unique(combined(words, n)))
        carry, at = words[-(n - 1) :], end
    if 0 < total < n:
        return combined(carry[-total:], total)
    return np.unique(np.concatenate(found)) if found else np.zeros(0, U)


def shingle_sets(texts: list[str | None], n: int = SHINGLE) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text; of fewer words, one of all; none without words."""
    raws = [t.encode("utf-8", "surrogatepass").lower() if t else b"" for t in texts]
    out: list[np.ndarray] = [np.zeros(0, U)] * len(raws)
    group, size = [], 0
    for i, r in enumerate(raws):
        if len(r) > PIECE // 4:
            out[i] = _whole(r, n)
            continue
        group.append(i)
        size += len(r)
        if size > PIECE // 8 or i == len(raws) - 1:
            _together(raws, group, n, out)
            group, size = [], 0
    _together(raws, group, n, out)
    return out


def _together(raws: list[bytes], group: list[int], n: int, out: list[np.ndarray]) -> None:
    if not group:
        return
    words, starts = word_hashes(b" ".join(raws[i] for i in group))
    begins = np.cumsum([0, *(len(raws[i]) + 1 for i in group)])
    cuts = np.searchsorted(starts, begins).tolist()
    grams = combined(words, n)
    for i, a, b in zip(group, cuts, cuts[1:]):
        if b - a >= n:
            g = np.sort(grams[a : b - n + 1])
            out[i] = g[np.concatenate([[True], g[1:] != g[:-1]])]
        elif b > a:
            out[i] = combined(words[a:b], b - a)


def fingerprint(s: np.ndarray) -> int:
    """A hash of a set as a signed long."""
    with np.errstate(over="ignore"):
        h = mix64(np.array([s.sum(dtype=U) + U(len(s)) * U(STEP)], U)) ^ np.bitwise_xor.reduce(mix64(s ^ U(BASE)))
    return int(mix64(h).astype(np.int64)[0])


def need(n, least: int):
    """ceil(t n)."""
    return (least * n + 99) // 100


def spare(n, least: int):
    """l: how many tokens beyond the needed prefix; grows with n, and no more than the tokens that a pair shares."""
    return np.minimum(need(n, least), np.maximum(n // SPARE, SPARE_LEAST))


def kept(n: int, least: int) -> int:
    return n - need(n, least) + int(spare(n, least))


SIGNED = "kind int, doc_id long, n long, fp long, th long, bucket int, flush long, fps binary, ns binary, owner binary, token binary, count binary"


def _short(tokens: np.ndarray) -> bytes:
    """The upper 48 bits of tokens.  The lower ones only tell apart what verification tells apart too."""
    return (tokens >> U(32)).astype(np.uint32).tobytes() + (tokens >> U(16)).astype(np.uint16).tobytes()


def _long(raw: bytes) -> np.ndarray:
    n = len(raw) // 6
    return (np.frombuffer(raw, np.uint32, n).astype(U) << U(32)) | (np.frombuffer(raw, np.uint16, n, 4 * n).astype(U) << U(16))


def _batch(ddl: str, size: int, /, **columns) -> pa.RecordBatch:
    """A batch of rows with the columns given; the others are null."""
    kinds = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary()}
    fields = [x.split() for x in ddl.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(columns[k], kinds[t]) if k in columns else pa.nulls(size, kinds[t]) for k, t in fields], names=[k for k, _ in fields])


def _table(ddl: str, rows: list[tuple]) -> pa.Table:
    names = [x.split()[0] for x in ddl.split(", ")]
    columns = zip(*rows, strict=True) if rows else [()] * len(names)
    return pa.Table.from_batches([_batch(ddl, len(rows), **dict(zip(names, columns, strict=True)))])


def _dealt(tokens: np.ndarray, buckets: int):
    """Places of tokens by bucket."""
    by = (mix64(tokens >> U(16)) % U(buckets)).astype(np.int64)
    order = np.argsort(by, kind="stable")
    heads = np.flatnonzero(np.concatenate([[True], by[order][1:] != by[order][:-1]]))
    for lo, hi in zip(heads.tolist(), [*heads.tolist()[1:], len(order)], strict=True):
        yield int(by[order[lo]]), order[lo:hi]


def _signed(batches, least: int, buckets: int, n: int):
    """Kind 0: a row for each text; kind 1: what a flush asks, by bucket; kind 2: a flush's sets and their kept tokens."""
    from pyspark import TaskContext

    part, ordinal = TaskContext.get().partitionId(), 0
    sets: dict[int, tuple[int, np.ndarray]] = {}
    held = 0

    def flush():
        flat = np.concatenate([t for _, t in sets.values()]) >> U(16) << U(16)
        owner = np.repeat(np.arange(len(sets)), [len(t) for _, t in sets.values()])
        tokens, count = np.unique(flat, return_counts=True)
        mark = (part << 32) + ordinal
        rows = [(k, _short(tokens[some]), count[some].astype(np.int32).tobytes()) for k, some in _dealt(tokens, buckets)]
        k, t, c = zip(*rows, strict=True)
        yield _batch(SIGNED, len(rows), kind=[1] * len(rows), flush=[mark] * len(rows), bucket=k, token=t, count=c)
        fps, ns = np.fromiter(sets, np.int64, len(sets)), np.array([x for x, _ in sets.values()], np.int64)
        yield _batch(SIGNED, 1, kind=[2], flush=[mark], fps=[fps.tobytes()], ns=[ns.tobytes()], owner=[owner.astype(np.int32).tobytes()], token=[_short(flat)])

    for b in batches:
        found = shingle_sets(b.column("text").to_pylist(), n)
        marks = [fingerprint(s) if len(s) else None for s in found]
        yield _batch(SIGNED, len(found), kind=[0] * len(found), doc_id=b.column("doc_id"), n=[len(s) for s in found], fp=marks, th=b.column("th"))
        for s, mark in zip(found, marks, strict=True):
            if len(s) and mark not in sets:
                sets[mark] = (len(s), s[: kept(len(s), least)].copy())
                held += len(sets[mark][1])
                if held > FLUSH:
                    yield from flush()
                    sets, held, ordinal = {}, 0, ordinal + 1
    if sets:
        yield from flush()


ANSWER = "flush long, token binary, count binary"


def _answered(table: pa.Table) -> pa.Table:
    """For each flush its tokens that occur in other sets too, with their frequency."""
    tokens = [_long(t) for t in table.column("token").to_pylist()]
    counts = [np.frombuffer(c, np.int32) for c in table.column("count").to_pylist()]
    every, at = np.unique(np.concatenate(tokens), return_inverse=True)
    df = np.bincount(at, np.concatenate(counts)).astype(np.int64)[at]
    rows, lo = [], 0
    for flush, t in zip(table.column("flush").to_pylist(), tokens, strict=True):
        mine = df[lo : lo + len(t)]
        lo += len(t)
        some = mine > 1
        if some.any():
            rows.append((flush, _short(t[some]), np.minimum(mine[some], (1 << 31) - 1).astype(np.int32).tobytes()))
    return _table(ANSWER, rows)


MET = "bucket int, a long, b long, fps binary, token binary"


def _stars(tokens: np.ndarray, fps: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The different tokens, the least fp of each, and links of that to the others."""
    order = np.lexsort((fps, tokens))
    tokens, fps = tokens[order], fps[order]
    head = np.concatenate([[True], tokens[1:] != tokens[:-1]])[: len(tokens)]
    least = fps[head][np.cumsum(head) - 1]
    links = np.unique(np.stack([least, fps], 1)[least != fps], axis=0)
    return tokens[head], fps[head], links


def _met(sets: pa.Table, answers: pa.Table, least: int, buckets: int) -> pa.Table:
    """Of a flush's sets with enough shared tokens the first ones in order of frequency: links, and one set for each token."""
    rows = []
    if len(answers):
        token = np.concatenate([_long(t) for t in answers.column("token").to_pylist()])
        df = np.concatenate([np.frombuffer(c, np.int32) for c in answers.column("count").to_pylist()])
        order = np.argsort(token)
        token, df = token[order], df[order]
        for row in sets.to_pylist():
            fps, ns = np.frombuffer(row["fps"], np.int64), np.frombuffer(row["ns"], np.int64)
            owner, mine = np.frombuffer(row["owner"], np.int32).astype(np.int64), _long(row["token"])
            at = np.minimum(np.searchsorted(token, mine), len(token) - 1)
            ok = token[at] == mine
            owner, mine, n = owner[ok], mine[ok], df[at[ok]]
            order = np.lexsort((mine, n, owner))
            owner, mine = owner[order], mine[order]
            shared = np.bincount(owner, minlength=len(fps))
            wanted = shared - spare(need(ns, least), least) + 1
            first = np.cumsum(shared) - shared
            ok = np.arange(len(owner)) - first[owner] < wanted[owner]
            tokens, heads, links = _stars(mine[ok], fps[owner[ok]])
            rows += [(-1, a, b, None, None) for a, b in links.tolist()]
            rows += [(k, None, None, heads[some].tobytes(), _short(tokens[some])) for k, some in (_dealt(tokens, buckets) if len(tokens) else ())]
    return _table(MET, rows)


def _linked(table: pa.Table) -> pa.Table:
    """Links between the sets that flushes passed on for one token."""
    tokens = np.concatenate([_long(t) for t in table.column("token").to_pylist()])
    fps = np.concatenate([np.frombuffer(f, np.int64) for f in table.column("fps").to_pylist()])
    links = _stars(tokens, fps)[2]
    return pa.Table.from_arrays([pa.array(links[:, 0]), pa.array(links[:, 1])], names=["a", "b"])


def _family_sets(batches, n: int):
    """Token sets of texts of members of families, each set once in a task."""
    done = set()
    for b in batches:
        sets = shingle_sets(b.column("text").to_pylist(), n)
        keep = []
        for i, (s, fp) in enumerate(zip(sets, b.column("fp").to_pylist(), strict=True)):
            if fp not in done and len(s) and fingerprint(s) == fp:
                done.add(fp)
                keep.append(i)
        some = b.take(pa.array(keep, pa.int64()))
        tokens = pa.array([sets[i].tobytes() for i in keep], pa.binary())
        yield pa.RecordBatch.from_arrays([*(some.column(c) for c in some.schema.names if c != "text"), tokens], names=[*(c for c in some.schema.names if c != "text"), "tokens"])


def links_between(fps: np.ndarray, sets: list[np.ndarray], label: np.ndarray, least: int) -> list[tuple[int, int]]:
    """Links that connect all similar sets; sets of one label count as connected.

    A candidate shares a prefix token with a set under each of three orders and has a label of its own.
    """
    sizes = np.array([len(s) for s in sets], np.int64)
    owner = np.repeat(np.arange(len(sets)), sizes)
    _, token, df = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    ends = np.cumsum(sizes)
    starts = ends - sizes
    hashed = np.argsort(np.argsort(mix64(np.arange(len(df), dtype=U) ^ U(INVERSE))))
    prefixes = []
    for order in (np.arange(len(df)), np.argsort(np.argsort(df, kind="stable")), hashed):
        ranked = np.lexsort((order[token], owner))
        early = np.arange(len(owner)) - starts[owner] < (sizes - need(sizes, least) + 1)[owner]
        early &= df[token[ranked]] > 1
        prefixes.append((owner[early], token[ranked][early]))
    bounds = [np.searchsorted(o, np.arange(len(sets) + 1)) for o, _ in prefixes]
    mark, found, label = np.zeros(len(df), bool), [], label.copy()
    after = np.arange(len(sets))
    for i in range(len(sets)):
        big, small = np.maximum(sizes, sizes[i]), np.minimum(sizes, sizes[i])
        open_ = (label != label[i]) & (after > i) & (100 * small >= least * big)
        for (o, t), edge in zip(prefixes, bounds, strict=True):
            if not open_.any():
                break
            mine = t[edge[i] : edge[i + 1]]
            mark[mine] = True
            open_ &= np.bincount(o[mark[t]], minlength=len(sets)) > 0
            mark[mine] = False
        candidates = np.flatnonzero(open_)
        if not len(candidates):
            continue
        mine = token[starts[i] : ends[i]]
        mark[mine] = True
        for j in candidates.tolist():
            if label[j] != label[i]:
                both = int(mark[token[starts[j] : ends[j]]].sum())
                if 100 * both >= least * (sizes[i] + sizes[j] - both):
                    found.append((int(fps[i]), int(fps[j])))
                    label[label == label[j]] = label[i]
        mark[mine] = False
    return found


def _compared(table: pa.Table, least: int) -> pa.Table:
    """Links within each family of a table; column label, if there, says what is connected already."""
    family, fps = table.column("family").to_numpy(), table.column("fp").to_numpy()
    label = table.column("label").to_numpy() if "label" in table.column_names else fps
    order = np.lexsort((fps, family))
    # A set that came more than once counts once.
    order = order[np.concatenate([[True], (fps[order][1:] != fps[order][:-1]) | (family[order][1:] != family[order][:-1])])]
    tokens, rows = table.column("tokens"), []
    heads = np.flatnonzero(np.concatenate([[True], family[order][1:] != family[order][:-1]])).tolist()
    for lo, hi in zip(heads, [*heads[1:], len(order)], strict=True):
        some = order[lo:hi]
        if len(some) > 1:
            rows += links_between(fps[some], [np.frombuffer(tokens[i].as_py(), U) for i in some.tolist()], label[some], least)
    return _table("a long, b long", rows)


def _buckets(documents: DataFrame) -> int:
    """As many buckets of tokens as the input has BUCKET_BYTES, and some for each shuffle partition."""
    size = int(str(documents._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return max(64, 2 * common.partitions(documents.sparkSession), size // BUCKET_BYTES if size < 1 << 60 else 0)


def _blocks(size, tokens):
    return F.ceil(F.greatest(size / BLOCK_SETS, tokens / BLOCK_TOKENS)).cast("int")


def families(signed: DataFrame, least: int, buckets: int) -> DataFrame:
    """fp and family of sets that share one of their first tokens with another, directly or through others."""
    answers = signed.where("kind = 1").select("bucket", "flush", "token", "count").groupBy("bucket").applyInArrow(_answered, ANSWER)
    sets = signed.where("kind = 2").select("flush", "fps", "ns", "owner", "token")
    met = common.cut(sets.groupBy("flush").cogroup(answers.groupBy("flush")).applyInArrow(lambda a, b: _met(a, b, least, buckets), MET), "met")
    across = met.where("bucket >= 0").select("bucket", "fps", "token").groupBy("bucket").applyInArrow(_linked, "a long, b long")
    stars = met.where("bucket < 0").select("a", "b").unionByName(across).distinct()
    found = components(stars)
    common.drop(met)
    return found.select(F.col("node").alias("fp"), F.col("component").alias("family"))


def _with_sets(docs: DataFrame, members: DataFrame, n: int) -> DataFrame:
    """family, fp, and the other columns of members, with tokens, from the texts of one row of each member."""
    columns = [f for f in members.schema.fields if f.name not in ("th", "low")]
    few = members.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
    other = members.withColumnsRenamed({"th": "its_th", "low": "its_id"})
    texts = docs.join(F.broadcast(other) if few else other, (docs["th"] == other["its_th"]) & docs["doc_id"].eqNullSafe(other["its_id"]))
    ddl = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in columns)
    return texts.select(*(f.name for f in columns), "text").mapInArrow(lambda batches: _family_sets(batches, n), f"{ddl}, tokens binary")


def _crossed(sets: DataFrame, links: DataFrame, least: int) -> tuple[DataFrame, list[DataFrame]]:
    """Links between different components of families of several blocks, and the tables that they are computed from."""
    found = components(links).select(F.col("node").alias("fp"), F.col("component").alias("label"))
    known = sets.select("family", "fp", "n").join(found, "fp", "left").withColumn("label", F.coalesce("label", "fp"))
    known = common.cut(known, "known")
    parts = known.groupBy("family", "label").agg(F.count("*").alias("size"), F.sum("n").alias("total"))
    parts = parts.withColumn("large", (F.col("size") > BLOCK_SETS // 2) | (F.col("total") > BLOCK_TOKENS // 2))
    mixed = parts.groupBy("family").agg(F.count("*").alias("n_parts"), F.sum(F.when(~F.col("large"), F.col("size"))).alias("m_size"), F.sum(F.when(~F.col("large"), F.col("total"))).alias("m_total")).where("n_parts > 1")
    parts = parts.join(mixed, "family")
    subs = F.when(F.col("large"), _blocks(F.col("size"), F.col("total"))).otherwise(_blocks(F.col("m_size"), F.col("m_total")))
    parts = parts.select("family", "label", F.when(F.col("large"), F.col("label")).alias("whole"), subs.alias("subs"))
    # A large component has blocks of its own; the others share blocks, each component in one of them.
    sub = F.when(F.col("whole").isNotNull(), F.pmod(F.xxhash64("fp"), F.col("subs"))).otherwise(F.pmod(F.xxhash64("label"), F.col("subs")))
    placed = known.join(parts, ["family", "label"]).select("family", "fp", "label", "whole", F.xxhash64(F.coalesce("whole", F.lit(0)), F.col("whole").isNull(), sub).alias("block"))
    placed = common.cut(placed, "crossed")
    blocks = placed.select("family", "block", "whole").distinct()
    others = blocks.select("family", F.col("block").alias("other"), F.col("whole").alias("other_whole"))
    pairs = blocks.join(others, "family").where((F.col("block") <= F.col("other")) & ~F.coalesce(F.col("whole") == F.col("other_whole"), F.lit(False)))
    pairs = pairs.select("family", F.col("block").alias("one"), F.col("other").alias("two"))
    sides = F.explode(F.array_distinct(F.array("one", "two"))).alias("block")
    meeting = placed.select("family", "fp", "label", "block").join(pairs.select("family", "one", "two", sides), ["family", "block"]).join(sets.select("fp", "tokens"), "fp")
    return meeting.groupBy("family", "one", "two").applyInArrow(lambda t: _compared(t.select(["family", "fp", "label", "tokens"]), least), "a long, b long"), [known, placed]


def _grouped(documents: DataFrame, least: int, n: int) -> tuple[DataFrame, DataFrame]:
    """doc_id, n and fp of each row; and of each set fp, its least doc_id (low), th of that row's text, and component."""
    spark = documents.sparkSession
    common.bound_batches(spark)
    buckets = _buckets(documents)
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.xxhash64("text").alias("th"))
    signed = common.cut(docs.mapInArrow(lambda batches: _signed(batches, least, buckets, n), SIGNED), "signed")
    rows = signed.where("kind = 0").select("doc_id", "n", "fp", "th")
    # Of each set the least id and the hash of that row's text, which find its text again.
    first = F.min(F.struct(F.col("doc_id").isNull().alias("nameless"), "doc_id", "th")).alias("first")
    classes = rows.where("n > 0").groupBy("fp").agg(first, F.first("n").alias("n"))
    classes = common.cut(classes.select("fp", "n", F.col("first.doc_id").alias("low"), F.col("first.th").alias("th")), "classes")
    members = classes.join(families(signed, least, buckets), "fp")
    members = common.cut(members, "members")
    sizes = members.groupBy("family").agg(F.count("*").alias("size"), F.sum("n").alias("total")).where("size > 1")
    placed = common.cut(members.join(sizes, "family").withColumn("n_blocks", _blocks(F.col("size"), F.col("total"))), "placed")
    counted = placed.agg(F.sum(F.when(F.col("n_blocks") == 1, F.col("n"))).alias("small"), F.count(F.when(F.col("n_blocks") > 1, 1)).alias("large")).first()
    bins = max(common.partitions(spark), -(-(counted.small or 0) // BLOCK_TOKENS))
    small = placed.where("n_blocks = 1").select("family", "fp", "th", "low", F.pmod(F.xxhash64("family"), F.lit(bins)).alias("bin"))
    links = _with_sets(docs, small, n).groupBy("bin").applyInArrow(lambda t: _compared(t.select(["family", "fp", "tokens"]), least), "a long, b long")
    used = [members, placed]
    if counted.large:
        leaders = F.greatest(F.lit(1), F.least(F.lit(LEADERS), F.floor(BLOCK_TOKENS / 4 * F.col("size") / F.col("total")))).cast("int")
        large = placed.where("n_blocks > 1").select("family", "fp", "th", "low", "n", "n_blocks", (F.pmod(F.xxhash64("fp", F.lit(7)), F.col("size")) < leaders).alias("leads"))
        sets = common.cut(_with_sets(docs, large, n), "sets")
        own = F.pmod(F.xxhash64("fp"), F.col("n_blocks")).cast("int")
        at = F.explode(F.when(F.col("leads"), F.sequence(F.lit(0), F.col("n_blocks") - 1)).otherwise(F.array(own))).alias("block")
        within = sets.select("family", "fp", "tokens", at).groupBy("family", "block").applyInArrow(lambda t: _compared(t.select(["family", "fp", "tokens"]), least), "a long, b long")
        within = common.cut(within, "within")
        across, more = _crossed(sets, within, least)
        links = links.unionByName(within).unionByName(across)
        used += [sets, within, *more]
    links = common.cut(links, "links")
    found = components(links).select(F.col("node").alias("fp"), "component")
    common.drop(*used, links)
    return rows, classes.select("fp", "low", "th").join(found, "fp", "left").withColumn("component", F.coalesce("component", "fp"))


def join(documents: DataFrame, least: int = LEAST, n: int = SHINGLE) -> DataFrame:
    """doc_id, n_shingles and component_id of each row, linked where 100 * intersection >= least * union.

    component_id is the least doc_id of rows whose sets are connected by links.  Null, empty and blank texts have an empty
    set and link with nothing; such a row's component is its own doc_id.  A row with a null doc_id links like any other,
    but lends no name: its component is null if no row in it has an id.  Repeated rows share a component; rows that repeat
    a doc_id with another text each have the component of their text.  Other columns are ignored.
    """
    rows, named = _grouped(documents, least, n)
    names = named.groupBy("component").agg(F.min("low").alias("name"))
    named = named.join(names, "component").select("fp", "name")
    out = rows.select("doc_id", "n", "fp").join(named, "fp", "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("name")).otherwise(F.col("doc_id")).alias("component_id"))


def keep_one(documents: DataFrame, least: int = LEAST, n: int = SHINGLE) -> DataFrame:
    """The input with one row of each component: the least doc_id, null last, then the least hash of its text.

    Of rows that repeat both doc_id and text the least in their other columns stays.  Rows whose set is empty (null, empty
    and blank texts) link with nothing, and all of them stay.  A column named th is replaced.
    """
    _, named = _grouped(documents, least, n)
    first = F.min(F.struct(F.col("low").isNull().alias("nameless"), "low", "th")).alias("first")
    chosen = named.groupBy("component").agg(first).select(F.col("first.low").alias("its_id"), F.col("first.th").alias("its_th"))
    columns = documents.columns
    blank = ~F.coalesce(F.col("text").rlike("[^\\x20\\x09-\\x0D]"), F.lit(False))
    docs = documents.withColumn("th", F.xxhash64("text"))
    kept = docs.where(~blank).join(chosen, F.col("doc_id").cast("long").eqNullSafe(F.col("its_id")) & (F.col("th") == F.col("its_th")), "left_semi")
    row = F.min(F.struct("text", *(F.col(c) for c in columns if c not in ("doc_id", "text")))).alias("row")
    return kept.groupBy("doc_id", "th").agg(row).select("doc_id", "row.*").select(columns).unionByName(docs.where(blank).select(columns))


def op6_shingle_join(spark, sf_dir: str) -> DataFrame:
    return join(common.read(spark, sf_dir, "documents"))


ORACLE_OP6 = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents),
s AS MATERIALIZED (
  SELECT DISTINCT doc_id, array_to_string(ws[i:i + 4], ' ') AS g
  FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 3, 2))) AS i FROM w WHERE len(ws) > 0)),
n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS MATERIALIZED (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
e AS MATERIALIZED (
  SELECT p.a, p.b FROM p JOIN n x ON x.doc_id = p.a JOIN n y ON y.doc_id = p.b WHERE 100 * p.c >= 80 * (x.n + y.n - p.c)),
r(doc_id, reached) AS (
  SELECT doc_id, doc_id FROM documents UNION SELECT r.doc_id, e.b FROM r JOIN e ON e.a = r.reached)
SELECT d.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, min(r.reached) AS component_id
FROM documents d LEFT JOIN n USING (doc_id) JOIN r USING (doc_id) GROUP BY d.doc_id, n.n"""
