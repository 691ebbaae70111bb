"""Piece encoding with seeded merge-dropout, and lossless decoding, for BPE models with byte fallback.

Text is taken as it is (no normalisation): a space in front, spaces as the model's space mark, characters without a
piece as byte pieces.  As no piece goes from a word character to another kind of character (checked when a model is
read), merges never cross the end of a run of word characters, so texts fall into chunks that are encoded alone.
Within a chunk an agenda holds the possible merges, best piece first, leftmost first; each one popped is skipped with
probability ``alpha``, decided by a keyed hash of the seed, the document, the chunk's position in it and the number of the
pop.  So each occurrence draws for each of its merges, and output depends on nothing but seed and input.  Ids depend on a
chunk and on which pops are skipped, so those with no skip or one are kept for later occurrences; all others are run,
thousands at a time.
"""

from __future__ import annotations

import hashlib
import heapq
import itertools
import pickle
import re
import struct

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from offsetlink.llm import common
from offsetlink.llm.common import SEED, mix64

ALPHA = 0.1
TOGETHER = 50_000  # chunks looked up and run at once
MOST_CHUNKS, MOST_ENTRIES = 120_000, 400_000  # kept between batches of a task; how many changes no result
PIECE = 1 << 20
MASK = (1 << 64) - 1
#: Word characters (but those that some piece continues with others), with what else stands before them.
CHUNK = re.compile(r"[^\w\n]*[^\W_²]+|(?:[^\w\n]|[_²])+[^\W_²]*|\n")


class Draws:
    """Which pops are skipped: gaps between skips are geometric, each drawn from 32 bits of a hash of the occurrence."""

    NEVER = 1 << 30
    STEP = 0x9E3779B97F4A7C15

    def __init__(self, alpha: float) -> None:
        limits = []  # 32 bits below the n-th limit: at least n pops before the next skip
        while alpha and (x := int((1 - alpha) ** (len(limits) + 1) * (1 << 32))):
            limits.append(x)
        self.alpha, self.rising = alpha, np.array(limits[::-1], np.uint64)

    def keys(self, seed: int, key: int, first: int, n: int) -> np.ndarray:
        """Hashes of n positions of a document."""
        with np.errstate(over="ignore"):
            own = mix64(np.array([((key * self.STEP) ^ (seed * 0xBF58476D1CE4E5B9)) & MASK], np.uint64))
            return mix64(own + np.arange(first + 1, first + n + 1, dtype=np.uint64) * np.uint64(self.STEP))

    def gaps(self, keys: np.ndarray, k) -> np.ndarray:
        """How many pops pass before skip k (from 0; one for all, or one each) since the one before."""
        if not self.alpha:
            return np.full(len(keys), self.NEVER)
        k = np.broadcast_to(np.asarray(k, np.uint64), keys.shape)
        with np.errstate(over="ignore"):
            h = np.where(k < 2, keys, mix64(keys + (k >> np.uint64(1)) * np.uint64(self.STEP)))
        bits = np.where(k & np.uint64(1), h >> np.uint64(32), h & np.uint64(0xFFFFFFFF))
        return len(self.rising) - np.searchsorted(self.rising, bits, "right")

    def skips(self, key: int):
        at = -1
        for k in itertools.count():
            at += 1 + int(self.gaps(np.array([key], np.uint64), k)[0])
            yield at


class Pieces:
    """The piece table of a model file: ids, merge ranks, bytes."""

    def __init__(self, model: bytes) -> None:
        from sentencepiece import SentencePieceProcessor

        sp = SentencePieceProcessor(model_proto=model)
        self.ids, self.rank, self.raw, self.byte = {}, {}, [], [0] * 256
        scores = {}
        for i in range(sp.get_piece_size()):
            piece = sp.id_to_piece(i)
            if sp.is_byte(i):
                self.byte[int(piece[3:5], 16)] = i
                self.raw.append(bytes([int(piece[3:5], 16)]))
            elif sp.is_control(i) or sp.is_unknown(i):
                self.raw.append(b"")
            else:
                plain = piece.replace("▁", " ")
                if re.search(r"[^\W_²][\W_²]", plain) or "\n" in plain.strip("\n"):
                    raise ValueError(f"piece {piece} crosses the end of a chunk")
                self.ids[plain] = i
                scores[plain] = sp.get_score(i)
                self.raw.append(plain.encode())
        self.rank = {p: -s for p, s in scores.items() if len(p) > 1}

    def chunk(self, text: str, seed: int = 0, variant: int = 0, alpha: float = 0.0) -> tuple[int, ...]:
        """Ids of one chunk, with a key from its text and a number."""
        key = int.from_bytes(hashlib.blake2b(text.encode("utf-8", "surrogatepass"), digest_size=8, key=b"%d:%d" % (seed, variant)).digest(), "little")
        return self.agenda(text, Draws(alpha).skips(key))[0]

    def agenda(self, text: str, skips) -> tuple[tuple[int, ...], int]:
        """Ids of one chunk whose pops of the given rising numbers are skipped, and the number of pops."""
        rank, pops, skips = self.rank, 0, iter(skips)
        skip = next(skips, -1)
        symbols: list[str | None] = list(text)
        n = len(symbols)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        agenda = [(rank[p], i, p) for i in range(n - 1) if (p := text[i : i + 2]) in rank]
        heapq.heapify(agenda)
        while agenda:
            _, i, piece = heapq.heappop(agenda)
            left = symbols[i]
            if left is None or (j := after[i]) >= n or len(left) + len(symbols[j]) != len(piece):
                continue  # one of its sides has been merged since
            pops += 1
            if pops - 1 == skip:
                skip = next(skips, -1)
                continue
            symbols[i], symbols[j] = piece, None
            after[i] = k = after[j]
            if k < n:
                before[k] = i
                if (p := piece + symbols[k]) in rank:
                    heapq.heappush(agenda, (rank[p], i, p))
            if (k := before[i]) >= 0 and (p := symbols[k] + piece) in rank:
                heapq.heappush(agenda, (rank[p], k, p))
        out: list[int] = []
        for s in symbols:
            if s is not None:
                if (x := self.ids.get(s)) is not None:
                    out.append(x)
                else:
                    out += [self.byte[b] for b in s.encode("utf-8", "surrogatepass")]
        return tuple(out), pops

    def decode(self, ids) -> str:
        """The text of ids: their bytes, without the space in front."""
        return b"".join(map(self.raw.__getitem__, ids))[1:].decode("utf-8", "surrogatepass")


class Merger:
    """Runs the agendas of many chunks at once: each step pops the best remaining pair of every chunk.

    A row holds a chunk's symbols as a linked list and the rank of each symbol's pair with the next one; pairs that have
    been skipped have no rank.  Gives what Pieces.agenda gives, as both skip the same pops and break ties to the left.
    Pairs are looked up by open addressing.
    """

    LONGEST = 32
    ROWS = 8192
    NONE = np.uint16(65535)
    SLOTS = 19

    def __init__(self, pieces: Pieces) -> None:
        self.byte, n = pieces.byte, len(pieces.raw)
        self.code = np.full(max((ord(p) for p in pieces.ids if len(p) == 1), default=0) + 2, -1, np.int32)
        for p, i in pieces.ids.items():
            if len(p) == 1:
                self.code[ord(p)] = i
        pairs = [((pieces.ids[p[:k]] << 15) + pieces.ids[p[k:]], pieces.ids[p], r) for p, r in pieces.rank.items() for k in range(1, len(p)) if p[:k] in pieces.ids and p[k:] in pieces.ids]
        order = sorted({x[2] for x in pairs})
        if n > 1 << 15 or len(order) >= self.NONE or 4 * len(pairs) > 1 << self.SLOTS:
            raise ValueError("the piece table is too large for the pair table")
        place = {r: k for k, r in enumerate(order)}
        keys = np.array([x[0] for x in pairs], np.int64)
        self.keys = np.full(1 << self.SLOTS, -1, np.int32)
        self.made, self.ranks = np.zeros(1 << self.SLOTS, np.int16), np.full(1 << self.SLOTS, self.NONE)
        slots, todo = self._slot(keys), np.arange(len(pairs))
        made, ranks = np.array([x[1] for x in pairs], np.int16), np.array([place[x[2]] for x in pairs], np.uint16)
        while len(todo):
            free = todo[self.keys[slots[todo]] < 0]
            self.keys[slots[free]] = keys[free]  # of those that want one slot, the last gets it
            mine = self.keys[slots] == keys
            self.made[slots[mine]], self.ranks[slots[mine]] = made[mine], ranks[mine]
            todo = todo[~mine[todo]]
            slots[todo] = (slots[todo] + 1) & ((1 << self.SLOTS) - 1)
        self.length = np.ones(n, np.int64)
        for p, i in pieces.ids.items():
            self.length[i] = len(p)

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return ((keys.astype(np.uint32) * np.uint32(0x9E3779B1)) >> np.uint32(32 - self.SLOTS)).astype(np.int64)

    def _ranked(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank (none if no piece) and piece of pairs of symbols; symbols below 0 are in no piece."""
        key = (left << 15) + right
        key[(left < 0) | (right < 0)] = -2
        slot = self._slot(key)
        there = self.keys[slot]
        more = np.flatnonzero((there != key) & (there >= 0))
        while len(more):
            slot[more] = (slot[more] + 1) & ((1 << self.SLOTS) - 1)
            there = self.keys[slot[more]]
            more = more[(there != key[more]) & (there >= 0)]
        rank = self.ranks[slot]
        rank[self.keys[slot] != key] = self.NONE
        return rank, self.made[slot]

    def run(self, chunks: list[str], keys: np.ndarray, alpha: float) -> list[bytes]:
        """Packed ids of chunks of at most LONGEST characters, with their keys."""
        ids, counts, *_ = self.encode(chunks, keys, Draws(alpha))
        blob, ends = ids.astype("<i4").tobytes(), np.cumsum(counts * 4).tolist()
        return [blob[e - 4 * n : e] for e, n in zip(ends, counts.tolist(), strict=True)]

    def encode(self, chunks: list[str], keys: np.ndarray, draws: Draws) -> tuple[np.ndarray, ...]:
        """For chunks of at most LONGEST characters: ids one after another, counts of ids, pops, skips, first skipped pop."""
        size = np.fromiter(map(len, chunks), np.int64, len(chunks))
        order = np.argsort(size, kind="stable")
        flat = np.frombuffer("".join(chunks).encode("utf-32-le", "surrogatepass"), np.uint32)
        flat = self.code[np.minimum(flat, len(self.code) - 1)]
        starts = np.cumsum(size) - size
        counts, pops, skipped, first = (np.zeros(len(chunks), np.int64) for _ in range(4))
        parts = []
        for i in range(0, len(order), self.ROWS):
            some = order[i : i + self.ROWS]
            sym = self._agendas(flat, starts[some], size[some], keys[some], draws, out := np.zeros((3, len(some)), np.int64))
            pops[some], skipped[some], first[some] = out
            kept = sym > -2
            counts[some] = kept.sum(1)
            odd = np.flatnonzero((sym == -1).any(1)).tolist()
            parts.append((some, sym[kept], {int(some[r]): sym[r][kept[r]] for r in odd}))
        # From the order of lengths back to that of the chunks; characters without a piece become bytes.
        plain = counts.copy()
        odd = {}
        for _, _, rows in parts:
            for r, row in rows.items():
                odd[r] = self._with_bytes(chunks[r], row)
                counts[r] = len(odd[r])
        ends = np.cumsum(counts)
        ids = np.zeros(int(ends[-1]) if len(ends) else 0, np.int32)
        for some, got, _ in parts:
            n, m = plain[some], counts[some]
            ids[_runs(ends[some] - m, np.minimum(n, m))] = got[_runs(np.cumsum(n) - n, np.minimum(n, m))]
        for r, row in odd.items():
            ids[ends[r] - len(row) : ends[r]] = row
        return ids, counts, pops, skipped, first

    def _with_bytes(self, chunk: str, row: np.ndarray) -> list[int]:
        out, at = [], 0
        for x in row.tolist():
            if x >= 0:
                out.append(x)
                at += int(self.length[x])
            else:
                out += [self.byte[b] for b in chunk[at].encode("utf-8", "surrogatepass")]
                at += 1
        return out

    def _agendas(self, flat: np.ndarray, starts: np.ndarray, size: np.ndarray, keys: np.ndarray, draws: Draws, out: np.ndarray) -> np.ndarray:
        """Final symbols of chunks (-2 where merged away or none); out gets pops, skips and the first skipped pop."""
        count, width = len(size), int(size.max())
        wide = width + 2  # a cell without symbol on either side
        sym = np.full((count, wide), -2, np.int32)
        grid = np.arange(wide)
        sym[:, 1:-1][grid[:width] < size[:, None]] = flat[_runs(starts, size)]
        rank, made = (x.reshape(count, wide - 1) for x in self._ranked(sym[:, :-1].ravel(), sym[:, 1:].ravel()))
        after, before = np.tile((grid + 1).astype(np.int8), (count, 1)), np.tile((grid - 1).astype(np.int8), (count, 1))
        flat_sym, flat_rank, flat_made, flat_after, flat_before = (x.reshape(-1) for x in (sym, rank, made, after, before))
        live, nth = np.arange(count), np.zeros(count, np.int64)
        skip = draws.gaps(keys, 0)
        out[2] = skip
        step = 0
        while True:
            j = (rank if len(live) == count else rank[live]).argmin(1)
            cell = live * (wide - 1) + j
            go = flat_rank[cell] != self.NONE
            if not go.all():
                out[0, live[~go]] = step
                live, j, cell, skip = live[go], j[go], cell[go], skip[go]
            if not len(live):
                break
            hit = skip == step
            if hit.any():
                flat_rank[cell[hit]] = self.NONE
                rows = live[hit]
                nth[rows] += 1
                skip[hit] = step + 1 + draws.gaps(keys[rows], nth[rows])
                rows, j, cell = live[~hit], j[~hit], cell[~hit]
            else:
                rows = live
            base = rows * wide
            flat_sym[base + j] = new = flat_made[cell].astype(np.int32)
            k = flat_after[base + j].astype(np.int64)
            flat_rank[rows * (wide - 1) + np.minimum(k, wide - 2)] = self.NONE
            flat_sym[base + k] = -2
            flat_after[base + j] = m = flat_after[base + k]
            m = m.astype(np.int64)
            flat_before[base + m] = j
            i = flat_before[base + j].astype(np.int64)
            flat_rank[cell], flat_made[cell] = self._ranked(new, flat_sym[base + m])
            cell = rows * (wide - 1) + np.maximum(i, 0)
            r, p = self._ranked(np.where(i >= 0, flat_sym[base + i], -2), new)
            flat_rank[cell[i >= 0]], flat_made[cell[i >= 0]] = r[i >= 0], p[i >= 0]
            step += 1
        out[1] = nth
        return sym


def _runs(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """All positions of runs, one run after another."""
    ends = np.cumsum(sizes)
    return np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(starts - (ends - sizes), sizes)


def packed(ids) -> bytes:
    """Ids as little-endian int32, which takes a fraction of the memory of a tuple."""
    return struct.pack(f"<{len(ids)}i", *ids)


class Known:
    """Ids of chunks without skips, and with one: the skipped pop picks a place in a chunk's row of a table."""

    def __init__(self) -> None:
        self.rows: dict[str, int] = {}
        self.ids, self.used, self.entries, self.places = np.zeros(1 << 16, np.int32), 0, 0, 0
        self.start, self.count, self.pops = (np.zeros(1 << 14, np.int64) for _ in range(3))  # of each entry
        self.entry, self.base, self.uses = (np.zeros(1 << 14, np.int64) for _ in range(3))  # of each row
        self.table = np.full(1 << 16, -1, np.int32)

    @staticmethod
    def _room(x: np.ndarray, n: int, fill: int = 0) -> np.ndarray:
        return x if n <= len(x) else np.concatenate([x, np.full(max(n - len(x), len(x)), fill, x.dtype)])

    def _add(self, ids: np.ndarray, counts: np.ndarray, pops: np.ndarray) -> np.ndarray:
        n, m = self.entries + len(counts), self.used + len(ids)
        self.ids, self.start, self.count, self.pops = self._room(self.ids, m), self._room(self.start, n), self._room(self.count, n), self._room(self.pops, n)
        self.ids[self.used : m] = ids
        self.start[self.entries : n] = self.used + np.cumsum(counts) - counts
        self.count[self.entries : n], self.pops[self.entries : n] = counts, pops
        at = np.arange(self.entries, n)
        self.entries, self.used = n, m
        return at

    def add_whole(self, chunks: list[str], ids: np.ndarray, counts: np.ndarray, pops: np.ndarray) -> None:
        first, n = len(self.rows), len(self.rows) + len(chunks)
        self.entry, self.base, self.uses = (self._room(x, n) for x in (self.entry, self.base, self.uses))
        self.entry[first:n], self.base[first:n], self.uses[first:n] = self._add(ids, counts, pops), self.places + np.cumsum(pops) - pops, 0
        self.places += int(pops.sum())
        self.table = self._room(self.table, self.places, -1)
        self.rows.update(zip(chunks, range(first, n), strict=True))

    def add_broken(self, places: np.ndarray, ids: np.ndarray, counts: np.ndarray, pops: np.ndarray) -> None:
        self.table[places] = self._add(ids, counts, pops)

    def full(self) -> bool:
        return len(self.rows) > MOST_CHUNKS or self.entries > MOST_ENTRIES

    def trimmed(self) -> Known:
        """Only the chunks used more than once since the last time; none, if those are most."""
        out, some = Known(), np.flatnonzero(self.uses[: len(self.rows)] > 1)
        if len(some) and 2 * len(some) <= MOST_CHUNKS:
            names, entry = list(self.rows), self.entry[some]
            out.add_whole([names[i] for i in some.tolist()], self.ids[_runs(self.start[entry], self.count[entry])], self.count[entry], self.pops[entry])
            was = self.table[_runs(self.base[some], self.pops[entry])]
            places = np.flatnonzero(was >= 0)
            if 2 * len(places) <= MOST_ENTRIES:
                entry = was[places]
                out.add_broken(places, self.ids[_runs(self.start[entry], self.count[entry])], self.count[entry], self.pops[entry])
        return out


def _chunks(text: str):
    """Lists of the chunks of a text; each slice of a long one ends where its last chunk begins."""
    at, size = 0, PIECE
    while at < len(text):
        some = CHUNK.findall(text, at, at + size)
        if at + size < len(text):
            if len(some) == 1:
                size *= 2
                continue
            some.pop()
        yield some
        at, size = at + sum(map(len, some)), PIECE


class Encoder:
    """Encodes texts with dropout; the same seed, document key and text give the same ids."""

    def __init__(self, pieces: Pieces, seed: int = SEED, alpha: float = ALPHA, merger: Merger | None = None) -> None:
        self.pieces, self.merger, self.seed, self.alpha, self.draws = pieces, merger or Merger(pieces), seed, alpha, Draws(alpha)
        self.known = Known()

    def encode_all(self, texts: list[str | None], keys: list[int]) -> tuple[np.ndarray, list[int]]:
        """Ids of all texts, one text after another, and how many each has."""
        done, counts = [np.zeros(0, np.int32)], [0] * len(texts)
        chunks, hashes, owners, sizes = [], [], [], []

        def flush() -> None:
            ids, n = self._encode(chunks, np.concatenate(hashes))
            done.append(ids)
            for o, c in zip(owners, np.add.reduceat(n, np.cumsum([0, *sizes[:-1]])).tolist(), strict=True):
                counts[o] += c
            for x in (chunks, hashes, owners, sizes):
                x.clear()

        for i, (text, key) in enumerate(zip(texts, keys, strict=True)):
            first = 0
            for some in _chunks(" " + text) if text else ():
                chunks += some
                hashes.append(self.draws.keys(self.seed, key, first, len(some)))
                owners.append(i)
                sizes.append(len(some))
                first += len(some)
                if len(chunks) >= TOGETHER:
                    flush()
        if chunks:
            flush()
        return np.concatenate(done), counts

    def _encode(self, chunks: list[str], hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of chunks, one chunk after another, and how many each has; what isn't known is run together."""
        if self.known.full():
            self.known = self.known.trimmed()
        known = self.known
        row = np.fromiter(map(known.rows.get, chunks, itertools.repeat(-1)), np.int64, len(chunks))
        skip, entry = self.draws.gaps(hashes, 0), np.full(len(chunks), -1, np.int64)
        there = np.flatnonzero(row >= 0)
        known.uses += np.bincount(row[there], minlength=len(known.uses))
        whole = known.entry[row[there]]
        fits = skip[there] >= known.pops[whole]
        entry[there[fits]] = whole[fits]
        broken = there[~fits]
        found = known.table[known.base[row[broken]] + skip[broken]]
        # With a second skip before the chunk's end the entry is of no use.
        again = skip[broken] + 1 + self.draws.gaps(hashes[broken], 1) < known.pops[found]
        entry[broken] = np.where(again, -1, found)
        start, count, pool = known.start[entry], known.count[entry], known.ids
        todo = np.flatnonzero(entry < 0)
        if len(todo):
            names = list(map(chunks.__getitem__, todo.tolist()))
            brief = np.fromiter(map(len, names), np.int64, len(names)) <= Merger.LONGEST
            short, extra, size = todo[brief], [], len(pool)
            if len(short):
                names = names if brief.all() else list(map(chunks.__getitem__, short.tolist()))
                ids, n, pops, skips, first = self.merger.encode(names, hashes[short], self.draws)
                start[short], count[short] = size + np.cumsum(n) - n, n
                extra.append(ids)
                size += len(ids)
                new = {names[i]: i for i in np.flatnonzero((row[short] < 0) & (skips == 0)).tolist()}
                some = np.fromiter(new.values(), np.int64, len(new))
                at = start[short] - len(pool)
                known.add_whole(list(new), ids[_runs(at[some], n[some])], n[some], pops[some])
                some = np.flatnonzero((row[short] >= 0) & (skips == 1))
                places, one = np.unique(known.base[row[short[some]]] + first[some], return_index=True)
                some = some[one]
                known.add_broken(places, ids[_runs(at[some], n[some])], n[some], pops[some])
            for i in todo[~brief].tolist():  # with its many skips, a long chunk is hardly ever met again
                ids = np.array(self.pieces.agenda(chunks[i], self.draws.skips(int(hashes[i])))[0], np.int32)
                start[i], count[i] = size, len(ids)
                extra.append(ids)
                size += len(ids)
            pool = np.concatenate([pool, *extra])
        return pool[_runs(start, count)], count

    def encode(self, text: str, key: int) -> list[int]:
        return self.encode_all([text], [key])[0].tolist()


def _encoded(batches, shared: bytes, seed: int, alpha: float):
    pieces, merger = pickle.loads(shared)
    encoder = Encoder(pieces, seed, alpha, merger)
    for b in batches:
        ids, counts = encoder.encode_all(b.column("text").to_pylist(), b.column("key").to_pylist())
        ends = pa.array(np.concatenate([[0], np.cumsum(counts)]).astype(np.int32))
        ids = pa.ListArray.from_arrays(ends, pa.array(ids), mask=b.column("text").is_null())
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("text"), ids], names=["doc_id", "text", "piece_ids"])


def encode(documents: DataFrame, seed: int = SEED, alpha: float = ALPHA, tokenizer_dir: str = common.TOKENIZER_DIR) -> DataFrame:
    """doc_id, text and piece_ids of each row.  Narrow: no shuffle, and each row alone decides its ids.

    Null text has null ids and empty text none; a null doc_id is keyed by the text's hash; repeated rows get the same
    ids.  Other columns are ignored.
    """
    rows, kind, model = _keyed(documents, tokenizer_dir)
    return rows.mapInArrow(lambda batches: _encoded(batches, model.value, seed, alpha), f"doc_id {kind}, text string, piece_ids array<int>")


def _keyed(documents: DataFrame, tokenizer_dir: str):
    spark = documents.sparkSession
    common.bound_batches(spark)
    pieces = Pieces(common.tokenizer_file("piece_bpe_32k.model", tokenizer_dir))
    model = common.share(spark, (pieces, Merger(pieces)))
    rows = documents.select("doc_id", "text", F.coalesce(F.col("doc_id").cast("long"), F.xxhash64("text")).alias("key"))
    return rows, documents.schema["doc_id"].dataType.simpleString(), model


class Decoder:
    """Turns lists of ids into texts, all of a column at once."""

    def __init__(self, pieces: Pieces) -> None:
        self.size = np.fromiter(map(len, pieces.raw), np.int64, len(pieces.raw))
        self.blob, self.place = np.frombuffer(b"".join(pieces.raw), np.uint8), np.cumsum(self.size) - self.size

    def texts(self, column: pa.ListArray) -> pa.Array:
        ids, counts = column.flatten().to_numpy(), np.array(pc.fill_null(pc.list_value_length(column), 0))
        sizes, starts = self.size[ids], self.place[ids]
        heads = (np.cumsum(counts) - counts)[counts > 0]
        sizes[heads] -= 1  # the space in front
        starts[heads] += 1
        ends = np.cumsum(sizes)
        raw = self.blob[np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(starts - (ends - sizes), sizes)]
        bounds = np.concatenate([[0], ends])[np.concatenate([[0], np.cumsum(counts)])]
        valid = pa.array(pc.is_valid(column).to_pylist(), pa.bool_()).buffers()[1]
        out = pa.LargeStringArray.from_buffers(len(column), pa.py_buffer(bounds.astype(np.int64)), pa.py_buffer(raw), valid)
        return out.cast(pa.string())


def _decoded(batches, model: bytes):
    decoder = Decoder(Pieces(model))
    for b in batches:
        texts = decoder.texts(b.column("piece_ids"))
        at = b.schema.get_field_index("decoded")
        yield b.set_column(at, "decoded", texts) if at >= 0 else b.append_column("decoded", texts)


def _round_trip(batches, shared: bytes, seed: int, alpha: float):
    decoder = Decoder(pickle.loads(shared)[0])
    for b in _encoded(batches, shared, seed, alpha):
        # In slices, as long texts have long lists of ids.
        for at in range(0, len(b), 250):
            some = b.slice(at, 250)
            yield some.append_column("decoded", decoder.texts(some.column("piece_ids")))


def round_trip(documents: DataFrame, seed: int = common.SEED, alpha: float = ALPHA, tokenizer_dir: str = common.TOKENIZER_DIR) -> DataFrame:
    """What decode(encode(documents)) gives, in one Python worker instead of two."""
    rows, kind, model = _keyed(documents, tokenizer_dir)
    return rows.mapInArrow(lambda batches: _round_trip(batches, model.value, seed, alpha), f"doc_id {kind}, text string, piece_ids array<int>, decoded string")


def decode(encoded: DataFrame, tokenizer_dir: str = common.TOKENIZER_DIR) -> DataFrame:
    """The input with a column decoded: the texts of piece_ids (replaced if there).  Null ids decode to null."""
    model = encoded.sparkSession.sparkContext.broadcast(common.tokenizer_file("piece_bpe_32k.model", tokenizer_dir))
    return _with_decoded(encoded, model)


def _with_decoded(encoded: DataFrame, model) -> DataFrame:
    from pyspark.sql.types import StringType, StructField, StructType

    fields = [f for f in encoded.schema.fields if f.name != "decoded"]
    schema = StructType([*fields, StructField("decoded", StringType())])
    return encoded.select(*[f.name for f in fields]).mapInArrow(lambda batches: _decoded(batches, model.value), schema)


def op1_merge_dropout(spark, sf_dir: str) -> DataFrame:
    """doc_id, n_pieces, ids_sha256 (of the ids, comma-joined), decoded_sha256, lossless; nulls where the text is null."""
    done = round_trip(common.read(spark, sf_dir, "documents"))
    return done.select(
        "doc_id", F.when(F.col("piece_ids").isNotNull(), F.size("piece_ids")).cast("long").alias("n_pieces"),
        F.sha2(F.array_join("piece_ids", ","), 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"), F.col("text").eqNullSafe(F.col("decoded")).alias("lossless"),
    )
