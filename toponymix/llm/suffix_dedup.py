"""Removal of repeated byte strings by threshold-bounded interval expansion on Burrows-Wheeler transforms.

Every string of `length` symbols has one anchor: its k-gram of smallest hash, leftmost on ties, which depends on the string
alone. Equal strings thus meet in the group of their anchor, and runs of strings with one anchor form one piece of text.
Groups with a single piece in the corpus hold no repeat and go first; copies of a piece are one piece with a count.
Groups with different pieces are indexed: a Burrows-Wheeler transform over a bounded batch of groups, on which
right-maximal intervals are extended backwards in breadth-first order, so that common prefixes come out by increasing
value; the expansion starts at the prefix length that the sort already tells apart and stops at `length`. Neighbours
whose common prefix was not settled by then share a string of that length. A group too large for a batch is settled by
exact counts of its strings' fingerprints instead.

Symbols are bytes, or words (`PASSAGE`): the word unit finds passages of 50 words that another document holds too, which
a byte threshold misses where words are short. It marks them and removes nothing.

Edge cases: null and empty texts keep zero bytes; texts shorter than `length` are kept whole; strings never cross
documents; overlapping repeats count; repeated rows (same id and text) are repeats of each other in bytes, and one document in
words; texts of any length are read in windows; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import _BYTE, materialise, mix, row_slices, scratch, signed, text_bytes, word_hashes


@dataclass(frozen=True)
class Unit:
    """What a string is made of: `length` symbols, anchored by `gram` of them; `across`: repeats count between documents only."""

    length: int
    gram: int
    words: bool = False
    across: bool = False

    @property
    def group_pieces(self) -> int:
        return GROUP_SYMBOLS // (2 * self.length)


PASSAGE = Unit(50, 16, words=True, across=True)
SLICE = 1 << 19
#: Symbols of a group's distinct pieces, of less than two lengths each, up to which it is indexed as a whole.
GROUP_SYMBOLS = 960_000
BATCH_SYMBOLS = 1 << 18
_POS = np.uint64((1 << 20) - 1)
_B = np.uint64(0x9E3779B97F4A7C15 | 1)
_powers: list[np.ndarray] = []


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base and of its inverse modulo 2^64, grown on demand."""
    if not _powers or len(_powers[0]) < n:
        inverse = np.uint64(pow(int(_B), -1, 2**64))
        _powers[:] = [np.cumprod(np.append(np.uint64(1), np.full(n, x, np.uint64)), dtype=np.uint64) for x in (_B, inverse)]
    return _powers[0], _powers[1]


class Hasher:
    """Fingerprints of all ranges of a buffer of symbols from one prefix sum."""

    def __init__(self, data: np.ndarray):
        self.up, self.down = powers(len(data) + 1)
        value = _BYTE[data] if data.dtype == np.uint8 else data
        self.sums = np.append(np.uint64(0), np.cumsum(value * self.up[: len(data)], dtype=np.uint64))

    def ranges(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((self.sums[end] - self.sums[start]) * self.down[start] + (end - start).astype(np.uint64))


def pieces(data: np.ndarray, offsets: np.ndarray, unit: Unit) -> tuple[np.ndarray, ...]:
    """(row, start in row, symbols, anchor hash, content hash) of the pieces of all rows of a buffer of at most 2^20 symbols."""
    none = tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, np.uint64, np.uint64))
    length = unit.length
    if len(data) < length:
        return none
    hasher = Hasher(data)
    at = np.arange(len(data) - unit.gram + 1)
    gram = hasher.ranges(at, at + unit.gram)
    key = (gram & ~_POS) | at.astype(np.uint64)
    w = length - unit.gram + 1
    padded = np.append(key, np.full(-len(key) % w, np.uint64(2**64 - 1))).reshape(-1, w)
    head = np.minimum.accumulate(padded, 1).ravel()
    tail = np.minimum.accumulate(padded[:, ::-1], 1)[:, ::-1].ravel()
    starts = np.arange(len(data) - length + 1)
    anchor = (np.minimum(tail[starts], head[starts + w - 1]) & _POS).astype(np.int64)
    row = np.searchsorted(offsets, starts, side="right") - 1
    inside = starts + length <= offsets[row + 1]
    starts, anchor, row = starts[inside], anchor[inside], row[inside]
    if not len(starts):
        return none
    new = np.append(True, (anchor[1:] != anchor[:-1]) | (row[1:] != row[:-1]))
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(starts)) - 1
    s, e = starts[first], starts[last] + length
    return row[first], s - offsets[row[first]], e - s, gram[anchor[first]], hasher.ranges(s, e)


def windows(offsets: np.ndarray, length: int) -> Iterator[tuple[int, int, int, int]]:
    """(first row, last row, from, to) of buffers of about SLICE symbols; long rows overlap by length - 1."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + SLICE, side="right")) - 1)
        if j == i + 1 and offsets[j] - offsets[i] > SLICE:
            a = int(offsets[i])
            while a + length <= offsets[j] or a == offsets[i]:
                b = min(a + SLICE, int(offsets[j]))
                yield i, i + 1, a, b
                if b == offsets[j]:
                    break
                a = b - length + 1
        else:
            yield i, j, int(offsets[i]), int(offsets[j])
        i = j


def symbols(batch: pa.RecordBatch, unit: Unit) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, symbols, offsets) of runs of rows of about a megabyte."""
    data, off = text_bytes(batch.column("text"))
    for i, j in row_slices(off):
        part, inner = data[off[i] : off[j]], off[i : j + 1] - off[i]
        if unit.words:
            part, counts = word_hashes(part, inner)
            inner = np.append(0, np.cumsum(counts))
        yield i, part, inner


def settle_order(data: np.ndarray, rest: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, int]:
    """Suffix order by at least `length` symbols, ranks by the first `depth` of them, and `depth`. rest: symbols to the piece's end.

    Bytes start from keys of seven of them, other symbols (small integers) from themselves.
    """
    n = len(data)
    k, key = 1, data
    if data.dtype == np.uint8:
        k, key = 7, np.zeros(n, np.uint64)
        for j in range(k):
            there = rest > j
            sym = np.zeros(n, np.uint64)
            sym[there] = data[np.flatnonzero(there) + j].astype(np.uint64) + np.uint64(1)
            key = (key << np.uint64(9)) | sym
    order = np.argsort(key)
    new = np.append(True, key[order[1:]] != key[order[:-1]])
    rank = np.empty(n, np.int64)
    rank[order] = np.maximum.accumulate(np.where(new, np.arange(n), 0))
    early, depth = rank, k
    while k < length:
        size = np.bincount(rank, minlength=n)
        todo = np.flatnonzero(size[rank] > 1)
        if not len(todo):
            break
        # Ranks of the next two stretches of k symbols refine the rank at once, so prefixes grow threefold a round.
        beyond = lambda d: np.where(rest[todo] > d, rank[np.minimum(todo + d, n - 1)] + 1, 0)
        both = (rank[todo] * np.int64(n + 1) + beyond(k)) * np.int64(n + 1) + beyond(2 * k)
        by = np.argsort(both)
        o, b = todo[by], both[by]
        group = rank[o]
        at = np.arange(len(o))
        head = np.maximum.accumulate(np.where(np.append(True, group[1:] != group[:-1]), at, 0))
        fresh = np.maximum.accumulate(np.where(np.append(True, b[1:] != b[:-1]), at, 0))
        rank = rank.copy()
        rank[o] = group + fresh - head
        k *= 3
        if k < length:
            early, depth = rank, k
    return np.argsort(rank), early, depth


def repeated_starts(data: np.ndarray, offsets: np.ndarray, length: int, owner: np.ndarray | None = None) -> np.ndarray:
    """Whether the string of `length` symbols at each position, inside its piece, is at another position of any piece too.

    With owners of the pieces, only strings count that pieces of two owners hold.
    """
    n = len(data)
    sizes = np.diff(offsets)
    rest = np.repeat(offsets[1:], sizes) - np.arange(n)
    order, early, depth = settle_order(data, rest, length)
    settled = np.append(True, early[order[1:]] != early[order[:-1]])  # boundaries whose common prefix is below `depth`
    # The transform: the symbol before each suffix, none at the start of a piece, and where that longer suffix stands.
    alphabet = int(data.max(initial=0)) + 1
    has = np.ones(n, bool)
    has[offsets[:-1][sizes > 0]] = False
    inverse = np.empty(n, np.int64)
    inverse[order] = np.arange(n)
    before = np.where(has[order], data[order - 1].astype(np.int64), -1)
    step = np.where(has[order], inverse[order - 1], -1)
    # Right-maximal intervals at `depth`, as runs of children: (node, first, end).
    same = ~settled
    nxt = np.where(rest[order] > depth, data[np.minimum(order + depth, n - 1)].astype(np.int64), -1 - np.arange(n))
    whole = rest[order] >= depth
    cut = settled | (nxt != np.append(-n - 2, nxt[:-1]))
    settled = settled | (same & cut & whole)
    child = np.flatnonzero(cut)
    child_end = np.append(child[1:], n)
    node = np.cumsum(~same)[child] - 1
    many = (np.bincount(node, minlength=int(node.max(initial=0)) + 1)[node] > 1) & whole[child]
    node, lo, hi = node[many], child[many], child_end[many]
    for _ in range(depth + 1, length):
        if not len(node):
            break
        width = hi - lo
        of = np.repeat(np.arange(len(lo)), width)
        at = lo[of] + np.arange(len(of)) - (np.cumsum(width) - width)[of]
        ok = before[at] >= 0
        of, at = of[ok], at[ok]
        if not len(of):
            break
        # Nodes come in ascending order and mostly extend by one symbol, so a stable sort has little to move.
        key = node[of] * alphabet + before[at]
        by = np.argsort(key, kind="stable")
        of, at, sym = of[by], at[by], key[by] % alphabet
        nn = node[of]
        new_node = np.append(True, (nn[1:] != nn[:-1]) | (sym[1:] != sym[:-1]))
        new_child = new_node | np.append(True, of[1:] != of[:-1])
        start = np.flatnonzero(new_child)
        # Beyond the sorted prefix the order inside a child is arbitrary, so its image is taken by extremes.
        image = step[at]
        node, lo, hi = (np.cumsum(new_node) - 1)[start], np.minimum.reduceat(image, start), np.maximum.reduceat(image, start) + 1
        many = np.bincount(node)[node] > 1
        node, lo, hi = node[many], lo[many], hi[many]
        if not len(node):
            break
        inner = np.append(False, node[1:] == node[:-1])
        settled[lo[inner]] = True
    full = rest[order] >= length
    pair = ~settled & full & np.append(False, full[:-1])
    out = np.zeros(n, bool)
    if owner is None:
        out[order[pair]] = True
        out[order[:-1][pair[1:]]] = True
    elif n:
        # Runs of neighbours that share their string: one entry with several owners settles all of the run.
        of, first = owner[np.repeat(np.arange(len(sizes)), sizes)][order], np.flatnonzero(~pair)
        several = np.minimum.reduceat(of, first) != np.maximum.reduceat(of, first)
        out[order[np.repeat(several, np.diff(np.append(first, n)))]] = True
    return out


def runs(mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    edge = np.diff(np.concatenate(([0], mask.view(np.int8), [0])))
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def occurrences(docs: DataFrame, unit: Unit, seen_most: int = 200_000) -> DataFrame:
    """(th, pos, n, h, c) of pieces; a piece surely repeated by what the task has met before comes without h and c."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[int, int] = {}
        for batch in batches:
            keys = batch.column("th").to_numpy()
            for first, sym, off in symbols(batch, unit):
                for i, j, a, b in windows(off, unit.length):
                    row, pos, n, h, c = pieces(sym[a:b], np.clip(off[i : j + 1], a, b) - a, unit)
                    if not len(row):
                        continue
                    pos = pos + (a - off[i] if j == i + 1 else 0)
                    own = keys[row + i + first]
                    again = np.zeros(len(row), bool)
                    for x, (key, th) in enumerate(zip((h * np.uint64(3) ^ c).tolist(), own.tolist(), strict=True)):
                        # None: two are on their way, of two documents where that matters.
                        if key not in seen:
                            seen[key] = th
                        elif seen[key] is None:
                            again[x] = True
                        elif not unit.across or seen[key] != th:
                            seen[key] = None
                    if len(seen) > seen_most:
                        seen.clear()
                    yield pa.RecordBatch.from_arrays([pa.array(own), pa.array(pos), pa.array(n), pa.array(signed(h), mask=again), pa.array(signed(c), mask=again)], ["th", "pos", "n", "h", "c"])

    return docs.select("th", "text").mapInArrow(run, "th long, pos long, n long, h long, c long")


def _filtered(rows: DataFrame, keys: DataFrame, key: str = "th", bits: int = 1 << 26) -> tuple[DataFrame, DataFrame]:
    """(rows that may have their key in keys, rows that surely have not), by a broadcast bitmap of fixed size."""
    place = F.pmod(F.xxhash64(key), F.lit(bits))
    slabs = keys.select(place.alias("p")).groupBy(F.floor(F.col("p") / 32768).cast("long").alias("slab")).agg(F.expr("bitmap_construct_agg(p % 32768)").alias("bits"))
    at = rows.withColumn("p", place).withColumn("slab", F.floor(F.col("p") / 32768).cast("long")).join(F.broadcast(slabs), "slab", "left")
    byte = F.conv(F.hex(F.expr("substring(bits, cast((p % 32768) div 8 as int) + 1, 1)")), 16, 10).cast("int")
    hit = F.coalesce(byte.bitwiseAND(F.expr("shiftleft(1, cast(p % 8 as int))")) != 0, F.lit(False))
    return at.where(hit).select(*rows.columns), at.where(~hit).select(*rows.columns)


def piece_bodies(docs: DataFrame, wanted: DataFrame, unit: Unit) -> DataFrame:
    """(h, c, own, body) of the pieces `wanted` (th, pos, n, h, c, own), cut from their documents' texts: each text moves once."""
    lists = wanted.groupBy("th").agg(F.collect_list(F.struct("pos", "n", "h", "c", "own")).alias("w"))
    some, _ = _filtered(docs.select("th", "text"), wanted.select("th"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            every = batch.column("w")
            for i, sym, off in symbols(batch, unit):
                part = every.slice(i, len(off) - 1)
                flat = part.flatten()
                pos, n = (flat.field(x).to_numpy() for x in ("pos", "n"))
                row = np.repeat(np.arange(len(part)), part.value_lengths().to_numpy())
                start = off[row] + pos
                body = pa.array([sym[x:y].tobytes() for x, y in zip(start, start + n, strict=True)], pa.binary())
                yield pa.RecordBatch.from_arrays([*(flat.field(x) for x in ("h", "c", "own")), body], ["h", "c", "own", "body"])

    return some.join(lists, "th").select("text", "w").mapInArrow(run, "h long, c long, own long, body binary")


RANGES = "h long, c long, ranges array<struct<s: long, e: long>>"
_STRUCT = pa.list_(pa.struct([("s", pa.int64()), ("e", pa.int64())]))


def index_groups(groups: DataFrame, unit: Unit) -> DataFrame:
    """(h, c, ranges) of pieces with repeats; rows arrive sorted by h and c, batches hold whole groups."""

    def settle(held: list[tuple[int, int, int, bytes]]) -> pa.RecordBatch:
        data = np.frombuffer(b"".join(x[3] for x in held), np.uint64 if unit.words else np.uint8)
        off = np.append(0, np.cumsum([len(x[3]) for x in held])) // data.itemsize
        if unit.words:
            data = np.unique(data, return_inverse=True)[1].astype(np.int64)
        hit = repeated_starts(data, off, unit.length, np.array([x[2] for x in held]) if unit.across else None)
        out = []
        for k, (h, c, _, _) in enumerate(held):
            s, e = runs(hit[off[k] : off[k + 1]])
            if len(s):
                out.append((h, c, [{"s": int(x), "e": int(y) + unit.length - 1} for x, y in zip(s, e, strict=True)]))
        return pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], t) for i, t in ((0, pa.int64()), (1, pa.int64()), (2, _STRUCT))], ["h", "c", "ranges"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[int, int, int, bytes]] = []
        size = 0
        for batch in batches:
            for x in zip(*(batch.column(k).to_pylist() for k in ("h", "c", "own", "body")), strict=True):
                if held and x[:2] == held[-1][:2]:
                    continue  # the same piece of a repeated row
                if size > BATCH_SYMBOLS and x[0] != held[-1][0]:
                    yield settle(held)
                    held, size = [], 0
                held.append(x)
                size += len(x[3]) // (8 if unit.words else 1)
        if held:
            yield settle(held)

    return groups.repartition("h").sortWithinPartitions("h", "c").mapInArrow(run, RANGES)


def count_strings(groups: DataFrame, unit: Unit) -> DataFrame:
    """(h, c, ranges) for groups of any size: fingerprints of all strings are counted across the cluster."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for h, c, own, b in zip(*(batch.column(k).to_pylist() for k in ("h", "c", "own", "body")), strict=True):
                data = np.frombuffer(b, np.uint64 if unit.words else np.uint8)
                at = np.arange(len(data) - unit.length + 1)
                f = signed(Hasher(data).ranges(at, at + unit.length))
                yield pa.RecordBatch.from_arrays([*(pa.array(np.full(len(at), x)) for x in (h, c, own)), pa.array(at), pa.array(f)], ["h", "c", "own", "at", "f"])

    rows = groups.dropDuplicates(["h", "c"]).select("h", "c", "own", "body").mapInArrow(run, "h long, c long, own long, at long, f long")
    twice = rows.groupBy("h", "f").agg(F.count(F.lit(1)).alias("k"), F.min("own").alias("lo"), F.max("own").alias("hi"))
    twice = twice.where("lo <> hi" if unit.across else "k > 1").select("h", "f")
    return rows.join(twice, ["h", "f"]).groupBy("h", "c").agg(F.collect_list(F.struct(F.col("at").alias("s"), (F.col("at") + unit.length).alias("e"))).alias("ranges"))


def repeated_ranges(spark: SparkSession, docs: DataFrame, unit: Unit) -> DataFrame:
    """(th, ranges): ranges (s, e) in symbols of docs (th, text) that repeated strings cover, several of a place possibly."""
    with scratch(spark) as kept:
        several = F.col("t0") != F.col("t1") if unit.across else F.col("k") > 1
        counts = [F.count(F.lit(1)).alias("k"), F.min("th").alias("t0"), F.max("th").alias("t1")]
        occ = kept(occurrences(docs, unit))
        shipped = occ.where(F.col("h").isNotNull())
        per = kept(shipped.groupBy("h").agg(*counts, F.min("c").alias("lo"), F.max("c").alias("hi")).where(several).select("h", (F.col("lo") != F.col("hi")).alias("mixed")))
        often = kept(_filtered(shipped, per, "h")[0].join(per, "h"))
        kinds = kept(often.where("mixed").groupBy("h", "c").agg(*counts, F.min(F.struct("th", "pos", "n")).alias("rep")).withColumn("whole", several))
        groups = kinds.groupBy("h").agg(F.count(F.lit(1)).alias("kinds"), F.bool_and("whole").alias("done")).where("not done").select("h", "kinds")
        own = F.when(F.col("t0") == F.col("t1"), F.col("t0")).otherwise(F.lit(-1)).alias("own")
        open_ = kept(kinds.join(groups, "h").select("rep.*", "h", "c", own, "kinds"))
        found = kept(index_groups(piece_bodies(docs, open_.where(F.col("kinds") <= unit.group_pieces), unit), unit))
        large = open_.where(F.col("kinds") > unit.group_pieces)
        if large.limit(1).count():
            found = found.unionByName(count_strings(piece_bodies(docs, large, unit), unit))

        whole = F.array(F.struct(F.lit(0).cast("long").alias("s"), F.col("n").alias("e")))
        # A group of one kind is repeated whole; of mixed groups, so are kinds that are repeated by themselves.
        plain = often.where("not mixed").select("th", "pos", whole.alias("ranges"))
        twice = often.where("mixed").join(kinds.where("whole").select("h", "c"), ["h", "c"]).select("th", "pos", whole.alias("ranges"))
        partly = often.where("mixed").join(found, ["h", "c"]).select("th", "pos", "ranges")
        local = occ.where(F.col("h").isNull()).select("th", "pos", whole.alias("ranges"))
        every = plain.unionByName(twice).unionByName(partly).unionByName(local)
        every = every.select("th", "pos", F.explode("ranges").alias("r")).select("th", F.struct((F.col("pos") + F.col("r.s")).alias("s"), (F.col("pos") + F.col("r.e")).alias("e")).alias("r"))
        return materialise(every.groupBy("th").agg(F.collect_set("r").alias("ranges")), spark)


def covered(ranges: str) -> Column:
    """The symbols that an array of ranges covers."""
    step = lambda t, r: F.struct((t["n"] + F.greatest(r["e"] - F.greatest(r["s"], t["to"]), F.lit(0).cast("long"))).alias("n"), F.greatest(t["to"], r["e"]).alias("to"))
    zero = F.lit(0).cast("long")
    return F.aggregate(F.array_sort(ranges), F.struct(zero.alias("n"), zero.alias("to")), step, lambda t: t["n"])


def cut_rows(rows: DataFrame) -> DataFrame:
    """Removes the ranges (array of s, e, any order) from each text and describes what is left."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, off = text_bytes(batch.column("text"))
            out = []
            for k, rs in enumerate(batch.column("ranges").to_pylist()):
                raw = data[off[k] : off[k + 1]]
                depth = np.zeros(len(raw) + 1, np.int32)
                if rs:
                    np.add.at(depth, [r["s"] for r in rs], 1)
                    np.add.at(depth, [r["e"] for r in rs], -1)
                gone = np.cumsum(depth)[: len(raw)] > 0
                out.append((len(raw), int(gone.sum()), len(runs(gone)[0]), hashlib.sha256(raw[~gone].tobytes()).hexdigest()))
            cols = [pa.array([o[i] for o in out], t) for i, t in ((0, pa.int64()), (1, pa.int64()), (2, pa.int64()), (3, pa.string()))]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("th"), *cols], ["doc_id", "th", *OUT])

    return rows.select("doc_id", "th", "text", "ranges").mapInArrow(run, "doc_id long, th long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


OUT = ["n_bytes", "n_removed", "n_spans", "kept_sha256"]


def dedup(spark: SparkSession, table: DataFrame, length: int = 400, passage: Unit | None = PASSAGE) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every row of table (doc_id, text).

    With `passage`, n_passage_words too: words inside passages of that length that another document holds.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    docs = table.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(F.coalesce("doc_id", F.lit(-1)), text).alias("th"), text.alias("text"))
    words = repeated_ranges(spark, docs, passage).select("th", covered("ranges").alias("n_passage_words")) if passage else None
    ranges = repeated_ranges(spark, docs, Unit(length, min(128, length)))
    touched, clean = _filtered(docs, ranges)
    zero = F.lit(0).cast("long")
    kept = clean.select("doc_id", "th", F.octet_length("text").cast("long").alias("n_bytes"), zero.alias("n_removed"), zero.alias("n_spans"), F.sha2("text", 256).alias("kept_sha256"))
    out = kept.unionByName(cut_rows(touched.join(ranges, "th", "left")))
    if words is None:
        return out.drop("th")
    return out.join(words, "th", "left").select("doc_id", *OUT, F.coalesce("n_passage_words", zero).alias("n_passage_words"))
