"""Set-similarity self-join on word n-gram shingles by universe partition and pigeonhole.

Sets of Jaccard similarity >= tau differ in at most H = (1-tau)/(1+tau) * (|r|+|s|) shingles. Per size band the shingle
universe is hashed into m > H segments, so at most H segments differ and the rest agree. Allocation, per band and by cost:

* exact segments: a set emits one signature for each of its first H+1 segments that hold enough shingles to be
  selective. Of two similar sets, one emits over the shorter run of segments; at most H of its H+1 differ, so one is
  equal, selective and emitted by both. A set with too few selective segments emits them all.
* one-deletion: fewer, wider segments, each with its own signature and those of all its one-shingle deletions; a
  segment then only fails when two or more differences fall into it. Chosen for small sets in populous bands.

Copies are one node (a set fingerprint). Each signature bucket is a star around its smallest node, so candidates grow
with the rows, not with the square of a group. All stars are verified on whole texts. Buckets that are not one component
then get stars around better-connected centres; clusters of members around a centre that are still several components
are compared whole, in blocks and by matrix products, so rows are made for links only. So no link between different texts is lost that could
change a component.

Edge cases: null and empty texts have no shingles and stay alone; a text shorter than the shingle width is one shingle;
rows with a null doc_id link like any other but never name a component, so one of such rows only has a null name; repeated
rows share a node; rows that share a doc_id but hold different texts are nodes of their own; an empty table gives an empty result; extra columns are
ignored. Nodes are 64-bit fingerprints of whole sets. Texts are fetched by the place of a row in the table (`rid`), so a
table must give its rows in the same order at each scan; a text that isn't the one of its node raises an error.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import materialise, mix, passing, row_slices, shingle_sets, signed, text_bytes, without_rows, word_hashes

#: Share of shingles that unrelated sets of a band have in common, for the cost model only.
COMMON = 0.05
#: Bits of the filter that keeps texts outside all candidate pairs from being shuffled; a fixed size of 8 MB.
FILTER_BITS = 1 << 26
#: The key of a row: its place in the table.
RID = F.monotonically_increasing_id


@dataclass(frozen=True)
class Threshold:
    """Similarity num/den on shingles of `width` words."""

    num: int = 85
    den: int = 100
    width: int = 4

    def differences(self, total: np.ndarray | int):
        """Most differing shingles of two similar sets whose sizes add up to `total`."""
        return (self.den - self.num) * total // (self.den + self.num)


@dataclass(frozen=True)
class Band:
    low: int
    high: int
    segments: int
    least: int
    deletions: bool


def band_edges() -> list[int]:
    edges = [1]
    while edges[-1] < 1 << 31:
        edges.append(max(edges[-1] + 1, edges[-1] * 3 // 2))
    return edges


def allocate(t: Threshold, low: int, high: int, population: int) -> Band:
    """The cheaper allocation of the band for `population` sets; no segments where only equal sets are similar."""
    h = int(t.differences(2 * high))
    if h == 0:
        return Band(low, high, 0, 0, False)

    def selective(m: int, least: int) -> float:
        lam = high / m
        p = math.exp(-lam) * sum(lam**i / math.factorial(i) for i in range(least))
        return m * (1 - p) - 4 * math.sqrt(m * p * (1 - p))

    exact = Band(low, high, h + 3, 1, False)
    for least in (2, 1):
        fit = next((m for m in range(h + 1, 2 * h + 12, max(1, h // 64)) if selective(m, least) >= h + 1), 0)
        if fit:
            exact = Band(low, high, fit, least, False)
            break
    wide = (h + 2) // 2
    cost = lambda rows, groups, held: population * rows + population**2 / 2 * groups * COMMON**held
    as_exact = cost(h + 1, h + 1, high / exact.segments)
    as_deleted = cost(high + wide, high + wide, max(high / wide - 1, 1))
    return Band(low, high, wide, 0, True) if as_deleted < as_exact else exact


def set_values(h: np.ndarray) -> np.ndarray:
    return mix(h ^ np.uint64(0x5851F42D4C957F2D))


def group_sums(key: np.ndarray, value: np.ndarray, n: int) -> np.ndarray:
    """Sums of 64-bit values by key, modulo 2^64, from exact sums of their halves."""
    low = np.bincount(key, (value & np.uint64(0xFFFFFFFF)).astype(np.float64), n).astype(np.uint64)
    high = np.bincount(key, (value >> np.uint64(32)).astype(np.float64), n).astype(np.uint64)
    return low + (high << np.uint64(32))


def fingerprints(h: np.ndarray, o: np.ndarray, rows: int) -> tuple[np.ndarray, np.ndarray]:
    """(size, fingerprint) of each row's set."""
    n = np.bincount(o, minlength=rows)
    return n, signed(mix(group_sums(o, set_values(h), rows) + n.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)))


def signatures(t: Threshold, bands: list[Band], h: np.ndarray, o: np.ndarray, n: np.ndarray, node: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(signature, node) rows of the sets given as (shingle, row) pairs with sizes n."""
    lows = np.array([b.low for b in bands])
    seg_of, least, cut = (np.array([getattr(b, f) for b in bands]) for f in ("segments", "least", "deletions"))
    highs = np.array([b.high for b in bands])
    own = np.searchsorted(lows, n, side="right") - 1
    out_sig, out_node = [], []
    value, spread = set_values(h), h >> np.uint64(32)
    step = 0
    while True:
        b = np.minimum(own + step, len(bands) - 1)
        member = (n > 0) & (own + step < len(bands)) & (t.num * lows[b] <= t.den * n)
        if not member.any():
            break
        step += 1
        m = np.where(member, seg_of[b], 0)
        if not m.any():
            continue
        base = np.cumsum(m) - m
        total = int(m.sum())
        used = m[o] > 0
        ou = o[used]
        key = base[ou] + ((spread[used] * m[ou].astype(np.uint64)) >> np.uint64(32)).astype(np.int64)
        v = value[used]
        held = np.bincount(key, minlength=total)
        sums = group_sums(key, v, total)
        row = np.repeat(np.arange(len(n)), m)
        salt = mix((b[row].astype(np.uint64) << np.uint64(40)) + (np.arange(total) - base[row]).astype(np.uint64))
        good = held >= np.maximum(least[b[row]], 1)
        rank = np.cumsum(good)
        before = np.append(0, rank)[base]
        need = t.differences(n + np.minimum(highs[b], t.den * n // t.num)) + 1
        enough = np.bincount(row, good, len(n)) >= need
        emit = np.where(enough[row], good & (rank - before[row] <= need[row]), True) | cut[b[row]]
        out_sig.append(mix(sums[emit] ^ salt[emit]))
        out_node.append(node[row[emit]])
        d = cut[b[ou]]
        if d.any():
            out_sig.append(mix((sums[key[d]] - v[d]) ^ salt[key[d]]))
            out_node.append(node[ou[d]])
    if not out_sig:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return signed(np.concatenate(out_sig)), np.concatenate(out_node)


def _sets_of(batch: pa.RecordBatch, t: Threshold, text: str) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    data, off = text_bytes(batch.column(text))
    for i, j in row_slices(off):
        words, counts = word_hashes(data[off[i] : off[j]], off[i : j + 1] - off[i])
        yield (i, j, *shingle_sets(words, counts, t.width))


def shingle_nodes(docs: DataFrame, t: Threshold, text: str = "text") -> DataFrame:
    """(rid, doc_id, n, node) of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, h, o in _sets_of(batch, t, text):
                n, node = fingerprints(h, o, j - i)
                own = [batch.column(c).slice(i, j - i) for c in ("rid", "doc_id")]
                yield pa.RecordBatch.from_arrays([*own, pa.array(n.astype(np.int64)), pa.array(node)], ["rid", "doc_id", "n", "node"])

    return docs.select(RID().alias("rid"), F.col("doc_id").cast("long"), text).mapInArrow(run, "rid long, doc_id long, n long, node long")


def signature_rows(docs: DataFrame, t: Threshold, bands: list[Band], text: str = "text") -> DataFrame:
    """(sig, node); a node already seen by the task is not emitted again, so copies collapse before the shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for batch in batches:
            for i, j, h, o in _sets_of(batch, t, text):
                n, node = fingerprints(h, o, j - i)
                fresh = np.zeros(j - i, bool)
                for r, x in enumerate(node.tolist()):
                    if n[r] and x not in seen:
                        seen.add(x)
                        fresh[r] = True
                if len(seen) > 200_000:
                    seen.clear()
                keep = fresh[o]
                sig, who = signatures(t, bands, h[keep], o[keep], np.where(fresh, n, 0), node)
                if len(sig):
                    yield pa.RecordBatch.from_arrays([pa.array(sig), pa.array(who)], ["sig", "node"])

    return docs.select(text).mapInArrow(run, "sig long, node long")


def _only(docs: DataFrame, ids: DataFrame, text: str) -> DataFrame:
    """(id, text) of rows whose rid may be in `ids`: a bitmap of fixed size is broadcast, never the ids."""
    place = lambda c: F.pmod(F.xxhash64(c), F.lit(FILTER_BITS))
    bits = ids.select(place(F.col("id")).alias("p")).groupBy(F.floor(F.col("p") / 32768).cast("long").alias("slab")).agg(F.expr("bitmap_construct_agg(p % 32768)").alias("bits"))
    at = docs.select(RID().alias("id"), F.col(text).alias("text")).withColumn("p", place(F.col("id")))
    at = at.withColumn("slab", F.floor(F.col("p") / 32768).cast("long"))
    byte = F.conv(F.hex(F.expr("substring(bits, cast((p % 32768) div 8 as int) + 1, 1)")), 16, 10).cast("int")
    return at.join(F.broadcast(bits), "slab").where(byte.bitwiseAND(F.expr("shiftleft(1, cast(p % 8 as int))")) != 0).select("id", "text")


def verify(spark: SparkSession, docs: DataFrame, pairs: DataFrame, t: Threshold, text: str = "text") -> DataFrame:
    """pairs (a, b of nodes; ra, rb of their rows) with `shared`, from whole texts; the centre a comes in runs."""
    ids = pairs.select(F.explode(F.array("ra", "rb")).alias("id"))
    some = _only(docs, ids, text)
    right = some.select(F.col("id").alias("rb"), F.col("text").alias("tb"))
    left = some.select(F.col("id").alias("ra"), F.col("text").alias("ta"))
    joined = pairs.join(right, "rb").join(left, "ra").select("a", "b", "na", "nb", "ra", "rb", "ta", "tb")

    def sets(column: pa.Array, nodes: pa.Array) -> list[np.ndarray]:
        data, off = text_bytes(column)
        out: list[np.ndarray] = []
        for i, j in row_slices(off):
            h, o = shingle_sets(*word_hashes(data[off[i] : off[j]], off[i : j + 1] - off[i]), t.width)
            if (fingerprints(h, o, j - i)[1] != nodes.slice(i, j - i).to_numpy()).any():
                raise RuntimeError("the table gave its rows in another order; write it out first")
            out += np.split(h, np.searchsorted(o, np.arange(1, j - i)))
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}
        for batch in batches:
            for k in range(0, batch.num_rows, 512):
                part = batch.slice(k, 512)
                ra = part.column("ra").to_numpy()
                new = [i for i in np.unique(ra, return_index=True)[1].tolist() if int(ra[i]) not in held]
                if new:
                    if len(held) > 64:
                        held.clear()
                        new = np.unique(ra, return_index=True)[1].tolist()
                    for i, s in zip(new, sets(part.column("ta").take(pa.array(new)), part.column("a").take(pa.array(new))), strict=True):
                        held[int(ra[i])] = s
                shared = [len(np.intersect1d(held[int(x)], s, assume_unique=True)) for x, s in zip(ra, sets(part.column("tb"), part.column("b")), strict=True)]
                yield pa.RecordBatch.from_arrays([*[part.column(c) for c in ("a", "b", "na", "nb")], pa.array(shared, pa.int64())], ["a", "b", "na", "nb", "shared"])

    return joined.mapInArrow(run, "a long, b long, na long, nb long, shared long")


def block_links(t: Threshold, left: list[tuple], right: list[tuple]) -> list[tuple[int, int]]:
    """Links between members (node, label, shingles) of two blocks: for each member one link to each other label."""

    def cells(block: list[tuple]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        n = np.array([len(m[2]) for m in block])
        return n, np.repeat(np.arange(len(block)), n), np.concatenate([m[2] for m in block])

    (n1, o1, h1), (n2, o2, h2) = cells(left), cells(right)
    both = np.intersect1d(h1, h2)
    shared = np.zeros((len(left), len(right)), np.float32)
    keep1, keep2 = np.isin(h1, both), np.isin(h2, both)
    v1, v2, o1, o2 = np.searchsorted(both, h1[keep1]), np.searchsorted(both, h2[keep2]), o1[keep1], o2[keep2]
    for at in range(0, len(both), 2048):
        one, two = np.zeros((len(left), 2048), np.float32), np.zeros((len(right), 2048), np.float32)
        in1, in2 = (v1 >= at) & (v1 < at + 2048), (v2 >= at) & (v2 < at + 2048)
        one[o1[in1], v1[in1] - at] = 1
        two[o2[in2], v2[in2] - at] = 1
        shared += one @ two.T
    i = shared.astype(np.int64)
    l1, l2 = np.array([m[1] for m in left]), np.array([m[1] for m in right])
    hit = (i * t.den >= (n1[:, None] + n2[None, :] - i) * t.num) & (l1[:, None] != l2[None, :])
    out: dict[tuple[int, int], tuple[int, int]] = {}
    for x, y in zip(*np.nonzero(hit), strict=True):
        out.setdefault((left[x][0], right[y][1]), (left[x][0], right[y][0]))
    return list(out.values())


def cluster_links(spark: SparkSession, docs: DataFrame, members: DataFrame, nodes: DataFrame, t: Threshold, text: str, block: int = 100_000) -> DataFrame:
    """(a, b) links between members of different labels in each cluster (a, node, label) around a centre.

    Members of a cluster are packed into blocks of about `block` shingles and 600 members at most; pairs of blocks are compared by matrix
    products, so no row is made for a pair of members unless it is a link.
    """
    sized = members.join(nodes.select("node", F.col("n"), F.col("rep").alias("id")), "node")
    spread = sized.groupBy("a").agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.greatest(F.ceil(F.sum("n") / block), F.ceil(F.count(F.lit(1)) / 600)).cast("int").alias("blocks")).where("lo <> hi")
    sized = materialise(sized.join(spread.select("a", "blocks"), "a").withColumn("blk", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")), spark)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, off = text_bytes(batch.column("text"))
            for i, j in row_slices(off):
                h, o = shingle_sets(*word_hashes(data[off[i] : off[j]], off[i : j + 1] - off[i]), t.width)
                cut = np.searchsorted(o, np.arange(j - i + 1))
                body = pa.array([h[x:y].tobytes() for x, y in zip(cut, cut[1:])], pa.binary())
                yield pa.RecordBatch.from_arrays([batch.column("id").slice(i, j - i), body], ["id", "body"])

    bodies = _only(docs, sized.select("id"), text).mapInArrow(pack, "id long, body binary")
    packed = sized.join(bodies, "id").groupBy("a", "blk", "blocks").agg(F.collect_list(F.struct("node", "label", "body")).alias("m"))
    packed = materialise(packed, spark)
    left = packed.select("a", F.col("m").alias("ml"), F.explode(F.sequence(F.col("blk"), F.col("blocks") - 1)).alias("blk"))
    pairs = left.join(packed.select("a", "blk", F.col("m").alias("mr")), ["a", "blk"]).select("ml", "mr")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def block_of(cell) -> list[tuple]:
            return [(m["node"], m["label"], np.frombuffer(m["body"], np.uint64)) for m in cell.as_py()]

        for batch in batches:
            for r in range(batch.num_rows):
                links = block_links(t, block_of(batch.column("ml")[r]), block_of(batch.column("mr")[r]))
                yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in links], pa.int64()) for i in (0, 1)], ["a", "b"])

    return materialise(pairs.mapInArrow(compare, "a long, b long").distinct(), spark)


def components(spark: SparkSession, edges: DataFrame, most: int = 60) -> DataFrame:
    """(node, label): the smallest node reachable; minimum labels over neighbours, then a jump to the label's label."""
    both = materialise(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), spark)
    labels = materialise(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("label")), spark)
    for _ in range(most):
        near = both.join(labels.select(F.col("node").alias("b"), F.col("label").alias("l")), "b").groupBy("a").agg(F.min("l").alias("l"))
        moved = labels.join(near, labels.node == near.a).select("node", F.col("label").alias("was"), F.least("label", "l").alias("via"))
        jump = labels.select(F.col("node").alias("via"), F.col("label").alias("far"))
        nxt = materialise(moved.join(jump, "via", "left").select("node", "was", F.least("via", "far").alias("label")), spark)
        labels = nxt.select("node", "label")
        if nxt.where("was <> label").limit(1).count() == 0:
            return labels
    raise RuntimeError("components did not settle; raise `most`")


def labelled_nodes(spark: SparkSession, docs: DataFrame, t: Threshold, text: str, hubs: int, turn: int | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """rows (rid, doc_id, n, node), nodes (node, n, rep: a row, least: the smallest doc_id), and (node, label) of linked nodes.

    `hubs` bounds the rounds that try a new centre per bucket, `turn` is about how many pairs are verified at once (none: all).
    """
    docs = docs.select("doc_id", text)
    rows = materialise(shingle_nodes(docs, t, text), spark)
    nodes = rows.where("n > 0").groupBy("node", "n").agg(F.min("rid").alias("rep"), F.min("doc_id").alias("least"))
    edges = band_edges()
    which = F.size(F.filter(F.array(*[F.lit(e) for e in edges[:-1]]), lambda e: e <= F.col("n"))) - 1
    population = {r.b: r.c for r in nodes.groupBy(which.alias("b")).agg(F.count(F.lit(1)).alias("c")).collect()}
    bands = [allocate(t, lo, hi - 1, population.get(i, 0) + population.get(i - 1, 0)) for i, (lo, hi) in enumerate(zip(edges, edges[1:]))]

    w = W.partitionBy("sig")
    starred = signature_rows(docs, t, bands, text).withColumns({"a": F.min("node").over(w), "z": F.max("node").over(w)}).where("a <> z")
    starred = starred.withColumn("wide", F.max((F.col("node") > F.col("a")) & (F.col("node") < F.col("z"))).over(w))
    starred = materialise(starred.select("sig", "a", "node", "wide"), spark)

    left = nodes.select(F.col("node").alias("a"), F.col("n").alias("na"), F.col("rep").alias("ra"))
    right = nodes.select(F.col("node").alias("b"), F.col("n").alias("nb"), F.col("rep").alias("rb"))
    fits = (F.col("na") * t.num <= F.col("nb") * t.den) & (F.col("nb") * t.num <= F.col("na") * t.den)

    def checked(pairs: DataFrame) -> DataFrame:
        sized = materialise(pairs.join(left, "a").join(right, "b").where(fits), spark)
        # Pairs are verified in turns, by centre, so that the texts of one turn alone lie in shuffle files.
        turns = min(16, 1 + sized.count() // turn) if turn else 1
        of = lambda k: sized.where(F.pmod(F.xxhash64("a"), F.lit(turns)) == k)
        return reduce(DataFrame.unionByName, [materialise(verify(spark, docs, of(k), t, text), spark) for k in range(turns)])

    linked = F.col("shared") * t.den >= (F.col("na") + F.col("nb") - F.col("shared")) * t.num
    stars = checked(starred.where("node <> a").select("a", F.col("node").alias("b")).distinct())  # the smallest node is a: a < b
    labels = components(spark, stars.where(linked))

    known = stars
    wide = materialise(starred.where("wide").select("sig", "node", "a"), spark)
    for _ in range(hubs + 1):
        # Buckets whose members are not yet one component.
        full = wide.join(labels.select("node", "label"), "node", "left").withColumn("label", F.coalesce("label", "node"))
        full = full.withColumns({"lo": F.min("label").over(w), "hi": F.max("label").over(w), "c": F.count("node").over(w)}).where("lo <> hi")
        full = materialise(full.select("sig", "node", "a", "label", "c"), spark)
        if hubs == 0 or full.limit(1).count() == 0:
            break
        # The next centre of a bucket is its member that shares most buckets with others: the likely origin of a group.
        degree = full.groupBy("node").agg(F.sum("c").alias("deg"))
        ranked = full.select("sig", "node").join(degree, "node").withColumn("a", F.max(F.struct("deg", "node")).over(w)["node"])
        moved = materialise(ranked.select("sig", "node", "a"), spark)
        fresh = moved.where("node <> a").select(F.least("a", "node").alias("a"), F.greatest("a", "node").alias("b")).distinct()
        fresh = fresh.join(known.select("a", "b"), ["a", "b"], "left_anti")
        got = checked(fresh)
        hubs -= 1
        if got.limit(1).count() == 0:
            hubs = 0
        known, wide = materialise(known.unionByName(got), spark), moved
        labels = components(spark, known.where(linked))

    apart = cluster_links(spark, docs, full.select("a", "node", "label").distinct(), nodes, t, text)
    if apart.limit(1).count():
        labels = components(spark, known.where(linked).select("a", "b").unionByName(apart))

    return rows, nodes, labels


def similar_components(spark: SparkSession, docs: DataFrame, t: Threshold = Threshold(), text: str = "text", hubs: int = 1) -> DataFrame:
    """(doc_id, n_shingles, component_id) of every row."""
    rows, nodes, labels = labelled_nodes(spark, docs, t, text, hubs)
    named = nodes.join(labels, "node")
    least = named.groupBy("label").agg(F.min("least").alias("component"))
    named = named.join(least, "label").select("node", "component")
    alone = nodes.join(named, "node", "left").select("node", F.coalesce("component", "least").alias("component"))
    return rows.join(alone, "node", "left").select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.coalesce("component", "doc_id")).otherwise(F.col("doc_id")).alias("component_id"))


def keep_representatives(spark: SparkSession, docs: DataFrame, t: Threshold = Threshold(80, 100, 5), turn: int = 100_000) -> DataFrame:
    """docs with one row of each component: the one of smallest id, null ids last, then the first in the table.

    Rows are told apart by their place, never by doc_id: different texts under one id are judged each by its own text, and a row
    with a null id goes only where it is a copy of another row. Rows without shingles stay, but repeats under one id are copies.
    """
    with passing(spark) as stays:
        rows, _, labels = labelled_nodes(spark, docs, t, "text", 1, turn)
        key = F.when(F.col("n") > 0, F.coalesce("label", "node")).otherwise(F.col("doc_id"))
        keyed = rows.join(labels, "node", "left").select("rid", "doc_id", (F.col("n") > 0).alias("some"), key.alias("key")).where(F.col("key").isNotNull())
        first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "rid"))["rid"]
        kept = keyed.groupBy("some", "key").agg(first.alias("first"), F.count(F.lit(1)).alias("c")).where("c > 1")
        gone = stays(keyed.join(kept, ["some", "key"]).where("rid <> first").select(F.col("rid").alias("_row")))
    return without_rows(docs, gone)


ORACLE = r"""
WITH RECURSIVE w AS (SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, unnest(list_transform(range(1, greatest(len(ws) - 3, 1) + 1), lambda k: array_to_string(ws[k:k + 3], ' '))) AS g FROM w WHERE len(ws) > 0),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
o AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
e AS (SELECT o.a, o.b FROM o JOIN n x ON x.doc_id = o.a JOIN n y ON y.doc_id = o.b WHERE 100 * i >= 85 * (x.n + y.n - i)),
r AS (SELECT doc_id, doc_id AS c FROM documents UNION SELECT r.doc_id, e.b FROM r JOIN e ON r.c = e.a)
SELECT r.doc_id, any_value(coalesce(n.n, 0)) AS n_shingles, min(r.c) AS component_id FROM r LEFT JOIN n USING (doc_id) GROUP BY 1
"""
