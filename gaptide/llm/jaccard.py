"""N-gram Jaccard self-join of documents and its connected groups, by count vectors and an R-tree.

A document is the set of its word shingles. Shingles are hashed into groups (as many as the set has shingles: with a
fixed number, chance alone would make large sets look alike); the number in each group makes the document a point, and
the sum of coordinate minima of two points bounds their overlap from above. Boxes of points in an R-tree, folded to a
quarter of the groups, bound whole sets of pairs at once; pairs that survive are bounded by their whole points, and then
verified on the whole sets. Groups are low bits of a hash, so a point folds to fewer groups.

An R-tree over all documents compares boxes of everything with everything, which grows with the square of the input, so
blocks come first and lose no pair: in one order of all shingles (common ones last, by a count sketch of fixed size over
all documents, then by hash) two sets that reach the similarity share several shingles among the first 5/16 of each, so
a document with fewer shared ones is like no other. Blocks whose documents are already joined to one group are dropped,
and the rest are joined through the tree.

No pairs within a dense group are listed: documents with equal sets count once, and before the tree join each block's
documents are tried against the block's first one only; what links there is one group from then on.

Cases: a null or blank text has an empty set and links with nothing; fewer words than a shingle make one shingle of the
whole; doc_id is a key (repeated whole rows count as one; rows that share it with different texts may share links); a null doc_id is in no group (component null); an empty
table gives an empty table; texts are read whole; other columns aren't read, and `one_of_each` returns them whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .base import cut, forget_others, fresh, mix64, release, shingles, ship, utf8, words

LEAST_GROUPS = 16
CELL_BITS, CELL_BLOCK = 19, 1 << 13
BITMAP = 1 << 25
SMALL_BLOCK = 256
#: Blocks of more documents are dealt in parts, and each pair of parts is a task's work.
LARGE_BLOCK = 4096
#: Shingles of a block beyond which it is dealt in parts too: points take a byte or two for each.
LARGE_BYTES = 32 << 20
#: Bytes of text that are hashed at once, and bytes of folded points that are compared at once.
AT_ONCE, POINT_BYTES = 1 << 20, 32 << 20


def point(s: np.ndarray) -> np.ndarray:
    """Number of shingles in each group, one group or two for each shingle; as many groups as keep each number within a byte."""
    g = max(LEAST_GROUPS, 1 << max(0, len(s) - 1).bit_length())
    while True:
        p = np.bincount((s & np.uint64(g - 1)).astype(np.int64), minlength=g)
        if p.max(initial=0) <= 255:
            return p.astype(np.uint8)
        g *= 2


def folded(p: np.ndarray, groups: int) -> np.ndarray:
    return p.astype(np.int32).reshape(-1, groups).sum(axis=0)


def lead_size(n: int) -> int:
    """Shingles at the head of a set's order in which each similar set shares at least least_shared(n)."""
    return min(n, n - (3 * n + 3) // 4 + 1 + n // 16) if n else 0


def least_shared(n):
    """Two sets that reach the similarity have an overlap of 3/4 of the larger and of 6/7 of the smaller at least. What of it lies behind the head that ends first is no more than the rest of that set, so 1 + n // 16 for the smaller n is within both heads; the partner of a set of n may have 3/4 of n."""
    return 1 + ((3 * n + 3) // 4) // 16


def parts_of(offsets: np.ndarray) -> Iterator[tuple[int, int]]:
    """Ranges of rows of about AT_ONCE bytes each, one row at least."""
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + AT_ONCE, side="right")) - 1)
        yield lo, min(hi, n)
        lo = min(hi, n)


def shingle_sets(column, width: int) -> Iterator[tuple[int, list[np.ndarray]]]:
    """First row and the sorted distinct shingle hashes of each row, a range of rows at a time."""
    forget_others()
    raw, offsets = utf8(column)
    for lo, hi in parts_of(offsets):
        own = offsets[lo : hi + 1] - offsets[lo]
        h, doc, _ = words(raw[offsets[lo] : offsets[hi]], own)
        s, owner = shingles(h, doc, hi - lo, width)
        ends = np.searchsorted(owner, np.arange(hi - lo + 1))
        yield lo, [np.unique(s[ends[i] : ends[i + 1]]) for i in range(hi - lo)]


def sketch(docs: DataFrame, width: int) -> tuple[np.ndarray, float]:
    """Counts of all shingles of all documents in a fixed number of cells; each task sums its own, blocks are summed in two steps."""
    cells = 1 << CELL_BITS

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, rows = np.zeros(cells, np.int64), 0
        for batch in batches:
            for _, sets in shingle_sets(batch.column(0), width):
                rows += len(sets)
                own += np.bincount((np.concatenate(sets) >> np.uint64(64 - CELL_BITS)).astype(np.int64), minlength=cells)
        if rows:
            blocks = own.reshape(-1, CELL_BLOCK)
            small = np.int32 if own.max() < 2**31 else np.int64
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(blocks), dtype=np.int32)), pa.array(np.full(len(blocks), hash(own.tobytes()[:4096]) & 31, np.int32)), pa.array([b.astype(small).tobytes() for b in blocks], pa.binary())], ["block", "lot", "counts"])

    def add(frame: pd.DataFrame) -> pd.DataFrame:
        total = np.zeros(CELL_BLOCK, np.int64)
        for c in frame["counts"]:
            total += np.frombuffer(c, np.int64 if len(c) == 8 * CELL_BLOCK else np.int32)
        return pd.DataFrame({"block": frame["block"].iloc[:1], "lot": frame["lot"].iloc[:1], "counts": [total.tobytes()]})

    schema = "block int, lot int, counts binary"
    first = docs.select("text").mapInArrow(count, schema).groupBy("block", "lot").applyInPandas(add, schema)
    # one row for each block: a fixed number of cells reaches the driver, whatever the input
    rows = first.withColumn("lot", F.lit(0)).groupBy("block").applyInPandas(add, schema).select("block", "counts").collect()
    out = np.zeros(cells, np.int64)
    for r in rows:
        out[r["block"] * CELL_BLOCK : (r["block"] + 1) * CELL_BLOCK] = np.frombuffer(r["counts"], np.int64)
    return out, out.mean()


def levels(counts: np.ndarray, mean: float) -> np.ndarray:
    """0 for cells as full as chance makes them, then a step for each doubling."""
    usual = mean + 6 * np.sqrt(mean) + 8
    return np.where(counts <= usual, 0, 1 + np.floor(np.log2(np.maximum(counts, 1) / usual))).clip(0, 30).astype(np.uint64)


def described(docs: DataFrame, level: np.ndarray, width: int) -> DataFrame:
    """doc_id, n, two hashes of the set, fine (its point) and lead (the head of its order)."""
    sent = docs.sparkSession.sparkContext.broadcast(level)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lv = sent.value
        for batch in batches:
            for lo, sets in shingle_sets(batch.column(1), width):
                n = [len(s) for s in sets]
                one, two, fine, lead = [], [], [], []
                for s in sets:
                    m = mix64(s + np.uint64(1))
                    one.append(m.sum(dtype=np.uint64).view(np.int64))
                    two.append(np.bitwise_xor.reduce(mix64(m ^ np.uint64(0xA5A5))).view(np.int64) if len(s) else 0)
                    fine.append(point(s).tobytes())
                    order = np.sort(lv[s >> np.uint64(64 - CELL_BITS)] << np.uint64(59) | (mix64(s) >> np.uint64(5)))
                    lead.append(order[: lead_size(len(s))].view(np.int64))
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(lo, len(sets)), pa.array(n, pa.int64()), pa.array(one, pa.int64()), pa.array(two, pa.int64()), pa.array(fine, pa.binary()), pa.array(lead, pa.list_(pa.int64()))],
                    ["doc_id", "n", "one", "two", "fine", "lead"],
                )

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, n long, one long, two long, fine binary, lead array<long>")


def bitmap(ids: DataFrame, place: Column) -> np.ndarray:
    """Which of BITMAP cells are taken: a filter of fixed size that lets some others through."""
    rows = ids.select(F.shiftright(place, 5).alias("w"), F.pmod(place, F.lit(32)).cast("int").alias("r")).select("w", F.expr("shiftleft(1L, r)").alias("b")).groupBy("w").agg(F.bit_or("b").alias("b"))
    t = rows.toArrow()
    out = np.zeros(BITMAP // 32, np.int64)
    out[t["w"].to_numpy()] = t["b"].to_numpy()
    return out.astype(np.uint32)


def taken(bits: np.ndarray, place: np.ndarray) -> np.ndarray:
    return (bits[place >> 5] >> (place & 31).astype(np.uint32)) & 1 != 0


def id_place(c: str) -> Column:
    return F.pmod(F.xxhash64(c), F.lit(BITMAP))


def postings(docs: DataFrame, shared: DataFrame) -> DataFrame:
    """doc_id, n, token: shingles of the heads that are in shared, of documents that have enough of them to be like another. Most are thrown out by a filter before any row is made of them."""
    sent = docs.sparkSession.sparkContext.broadcast(bitmap(shared, F.col("token").bitwiseAND(F.lit(BITMAP - 1))))

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = sent.value
        for batch in batches:
            lead = batch.column(2)
            token, size = lead.flatten().to_numpy(zero_copy_only=False), np.diff(lead.offsets.to_numpy())
            hit, row = taken(bits, token & (BITMAP - 1)), np.repeat(np.arange(len(size)), size)
            many = np.bincount(row, hit, len(size)) >= least_shared(batch.column(1).to_numpy())
            hit = np.flatnonzero(hit & many[row])
            row = pa.array(row[hit])
            yield pa.RecordBatch.from_arrays([batch.column(0).take(row), batch.column(1).take(row), pa.array(token[hit])], ["doc_id", "n", "token"])

    return docs.select("doc_id", "n", "lead").mapInArrow(keep, "doc_id long, n long, token long").join(shared, "token", "left_semi")


def sets_of(docs: DataFrame, wanted: DataFrame, width: int) -> DataFrame:
    """doc_id and its packed sorted set, for the ids in wanted (a column doc_id) and a few others."""
    sent = docs.sparkSession.sparkContext.broadcast(bitmap(wanted, id_place("doc_id")))

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = sent.value
        for batch in batches:
            at = batch.column(1).to_numpy()
            hit = np.flatnonzero(taken(bits, at))
            if len(hit):
                few = batch.take(pa.array(hit))
                for lo, sets in shingle_sets(few.column(2), width):
                    yield pa.RecordBatch.from_arrays([few.column(0).slice(lo, len(sets)), pa.array([s.tobytes() for s in sets], pa.binary())], ["doc_id", "members"])

    rows = docs.where(F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long"), F.col("text").cast("string")).select("doc_id", id_place("doc_id").alias("place"), "text")
    return rows.mapInArrow(keep, "doc_id long, members binary")


def verified(docs: DataFrame, pairs: DataFrame, width: int, lot: int = 200) -> DataFrame:
    """The pairs (a, b) whose whole sets reach the similarity. A document with many partners gets them in lots, each with a copy of its own set."""
    pairs = cut(pairs)
    lots = pairs.groupBy("a").agg(F.ceil(F.count(F.lit(1)) / lot).cast("int").alias("lots"))
    heads = lots.select(F.col("a").alias("doc_id"), "a", F.explode(F.sequence(F.lit(0), F.col("lots") - 1)).alias("lot"), F.lit(None).cast("long").alias("b"))
    partners = pairs.join(lots, "a").select(F.col("b").alias("doc_id"), "a", F.pmod(F.xxhash64("b"), F.col("lots")).cast("int").alias("lot"), "b")
    roles = cut(heads.union(partners))
    rows = sets_of(docs, roles, width).join(roles, "doc_id").select("a", "lot", "b", "members")

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, own = None, []
        for batch in batches:
            links: list[tuple[int, int]] = []
            for a, part, b, m in zip(*(c.to_pylist() for c in batch.columns)):
                other = np.frombuffer(m, np.uint64)
                if b is None:  # the head's own set comes before its partners
                    own = [*own, other] if now == (a, part) else [other]
                    now = (a, part)
                elif any(7 * len(np.intersect1d(x, other, assume_unique=True)) >= 3 * (len(x) + len(other)) for x in own):
                    links.append((a, b))
            yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in links], pa.int64()), pa.array([y for _, y in links], pa.int64())], ["a", "b"])

    dealt = rows.repartition("a", "lot").sortWithinPartitions("a", "lot", F.col("b").asc_nulls_first())
    return cut(dealt.mapInArrow(check, "a long, b long").distinct())


def components(edges: DataFrame) -> DataFrame:
    """node and root (the smallest node reachable) of every node of the edges (a, b), by stars in turn: neighbours above a node move to its least neighbour, then those below."""
    e = cut(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    mark = lambda x: tuple(x.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v"))).first())
    seen = mark(e)
    while True:
        both = e.select(F.col("u").alias("x"), F.col("v").alias("y")).union(e.select("v", "u"))
        low = both.groupBy("x").agg(F.min("y").alias("m"))
        large = both.where("y > x").join(low, "x").select(F.col("y").alias("u"), F.least("m", "x").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        joined = large.join(low, "u")
        e = cut(joined.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v"))).distinct())
        now = mark(e)
        if now == seen:
            break
        seen = now
    return e.select(F.col("u").alias("node"), F.col("v").alias("root"))


class CountTree:
    """Packed R-tree over count vectors; a box keeps the greatest count of each group and the range of set sizes."""

    def __init__(self, points: np.ndarray, sizes: np.ndarray, leaf: int = 16):
        spread = points.max(axis=0).astype(np.int64) - points.min(axis=0) if len(points) else np.zeros(points.shape[1], np.int64)
        axes = np.argsort(-spread)[:2]
        slab = np.floor(np.log(np.maximum(sizes, 1)) / np.log(1.08)).astype(np.int64)
        self.order = np.lexsort((points[:, axes[1]], points[:, axes[0]], slab))
        self.points, self.sizes = points[self.order], sizes[self.order]
        self.at = np.arange(0, len(points), leaf)
        self.upper = np.maximum.reduceat(self.points, self.at, axis=0)
        self.low, self.high = np.minimum.reduceat(self.sizes, self.at), np.maximum.reduceat(self.sizes, self.at)
        self.top_at = np.arange(0, len(self.at), leaf)
        self.top_upper = np.maximum.reduceat(self.upper, self.top_at, axis=0)
        self.top_low, self.top_high = np.minimum.reduceat(self.low, self.top_at), np.maximum.reduceat(self.high, self.top_at)
        self.leaf = leaf

    @staticmethod
    def may(box: np.ndarray, low: int, high: int, upper: np.ndarray, lows: np.ndarray, highs: np.ndarray) -> np.ndarray:
        """Whether two boxes may hold a similar pair: sizes within 3 to 4, overlap bound high enough for the least sizes."""
        fit = (4 * highs >= 3 * low) & (4 * high >= 3 * lows)
        fit[fit] = 7 * np.minimum(upper[fit], box).sum(axis=1) >= 3 * (low + lows[fit])
        return fit

    def pairs(self, group: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Places (into the input) of pairs that may be similar and are of different groups, each pair once."""
        group, n = group[self.order], len(self.order)
        for k, lo in enumerate(self.at):
            hi = min(lo + self.leaf, n)
            tops = np.flatnonzero(self.may(self.upper[k], self.low[k], self.high[k], self.top_upper, self.top_low, self.top_high))
            leaves = np.concatenate([np.arange(t * self.leaf, min((t + 1) * self.leaf, len(self.at))) for t in tops]) if len(tops) else np.zeros(0, np.int64)
            leaves = leaves[leaves >= k]
            if len(leaves):
                leaves = leaves[self.may(self.upper[k], self.low[k], self.high[k], self.upper[leaves], self.low[leaves], self.high[leaves])]
            most = max(1, min(64, POINT_BYTES // (8 * self.leaf * self.leaf * self.points.shape[1])))
            for some in np.array_split(leaves, -(-len(leaves) // most)):
                if not len(some):
                    continue
                other = np.concatenate([np.arange(self.at[x], min(self.at[x] + self.leaf, n)) for x in some])
                bound = np.minimum(self.points[lo:hi, None, :], self.points[None, other, :]).sum(axis=2)
                ok = (7 * bound >= 3 * (self.sizes[lo:hi, None] + self.sizes[None, other])) & (group[lo:hi, None] != group[None, other]) & (np.arange(lo, hi)[:, None] < other[None, :])
                i, j = np.nonzero(ok)
                if len(i):
                    yield self.order[lo + i], self.order[other[j]]


def near_points(raw: list[np.ndarray], some: np.ndarray, groups: int, sizes: np.ndarray, roots: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of places in some that the tree over a quarter of the groups and then the bound by all of them let through."""
    fine, n = np.stack([folded(raw[i], groups) for i in some]), sizes[some]
    step = max(1, min(4096, POINT_BYTES // (8 * groups)))
    for i, j in CountTree(fine.reshape(len(some), -1, max(LEAST_GROUPS, groups // 4)).sum(axis=1), n).pairs(roots[some]):
        for lo in range(0, len(i), step):
            p, q = i[lo : lo + step], j[lo : lo + step]
            ok = 7 * np.minimum(fine[p], fine[q]).sum(axis=1) >= 3 * (n[p] + n[q])
            yield p[ok], q[ok]


def block_pairs(ids: np.ndarray, own: np.ndarray, sizes: np.ndarray, roots: np.ndarray, part: np.ndarray, points: np.ndarray) -> Iterator[np.ndarray]:
    """Pairs of a block that neither the tree nor the fine points rule out. Similar sets have points of one length or of neighbouring ones, so each length is taken with the next."""
    if len(ids) < 2 or (roots == roots[0]).all():
        return
    alone = (part == part[0]).all()
    raw = [np.frombuffer(x, np.uint8) for x in points]
    length = np.array([len(x) for x in raw])
    for g in np.unique(length):
        some = np.flatnonzero((length == g) | (length == 2 * g))
        if len(some) < 2 or (roots[some] == roots[some[0]]).all():
            continue
        # points of long documents are many bytes: as many documents at a time as have room, and each lot with each later one
        room = max(16, POINT_BYTES // (8 * int(g)))
        lots = np.array_split(some, -(-len(some) // room))
        for first in range(len(lots)):
            for then in range(first, len(lots)):
                both = lots[first] if first == then else np.concatenate((lots[first], lots[then]))
                lot = np.arange(len(both)) >= len(lots[first])
                for p, q in near_points(raw, both, int(g), sizes, roots):
                    # a pair of two guests is met in their own block, one of the same part in the part's own cell, one of the same lot by itself
                    x, y = both[p], both[q]
                    keep = ((length[x] == g) | (length[y] == g)) & (own[x] | own[y]) & ((part[x] != part[y]) | alone) & ((lot[p] != lot[q]) | (first == then))
                    a, b = ids[x[keep]], ids[y[keep]]
                    yield np.stack([np.minimum(a, b), np.maximum(a, b)])


def tree_candidates(members: DataFrame) -> DataFrame:
    """Pairs (a, b) of documents of different groups (column root) in one block (key) that the tree can't rule out.

    members has key, size (documents of the block), weight (their shingles), doc_id, n, root, fine. A block of more than
    SMALL_BLOCK is split by bands of sizes, one of more than LARGE_BLOCK or LARGE_BYTES also in pairs of parts; a document is in its own band's part and a guest in the next one's: similar
    sets are at most a band apart.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest: list[list[np.ndarray]] = []

        def done(parts: list[list[np.ndarray]]) -> Iterator[pa.RecordBatch]:
            key, at, own, ids, sizes, roots, part, points = (np.concatenate(x) for x in zip(*parts))
            ends = np.flatnonzero(np.concatenate(([True], (key[1:] != key[:-1]) | (at[1:] != at[:-1]), [True])))
            found = [x for lo, hi in zip(ends, ends[1:]) for x in block_pairs(ids[lo:hi], own[lo:hi], sizes[lo:hi], roots[lo:hi], part[lo:hi], points[lo:hi])]
            both = np.unique(np.concatenate(found, axis=1), axis=1) if found else np.zeros((2, 0), np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(both[0]), pa.array(both[1])], ["a", "b"])

        for batch in batches:
            if not batch.num_rows:
                continue
            cols = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(7)]
            cols.append(np.array(batch.column(7).to_pylist(), object))
            # the last block of a batch may go on in the next one
            new = np.flatnonzero((cols[0] != cols[0][-1]) | (cols[1] != cols[1][-1]))
            split = int(new[-1]) + 1 if len(new) else 0
            same = rest and rest[0][0][-1] == cols[0][0] and rest[0][1][-1] == cols[1][0]
            if rest and not (same and split == 0):
                if same:
                    yield from done([*rest, [c[:split] for c in cols]])
                else:
                    yield from done(rest)
                    if split:
                        yield from done([[c[:split] for c in cols]])
                rest = [[c[split:] for c in cols]]
            elif rest:
                rest.append(cols)
            else:
                if split:
                    yield from done([[c[:split] for c in cols]])
                rest = [[c[split:] for c in cols]]
        if rest:
            yield from done(rest)

    band = F.floor(F.log(F.col("n").cast("double")) / F.log(F.lit(4 / 3))).cast("int")
    at = lambda b, own: F.struct(b.alias("at"), F.lit(own).alias("own"))
    split = F.when(F.col("size") > SMALL_BLOCK, F.array(at(band, True), at(band + 1, False))).otherwise(F.array(at(F.lit(-1), True)))
    rows = members.select("*", F.explode(split).alias("x")).select("key", "size", "weight", F.col("x.at").alias("band"), F.col("x.own").alias("own"), "doc_id", "n", "root", "fine")
    # a large block: a document goes to each pair of parts that its own is in
    parts = F.greatest(F.lit(1), F.ceil(F.col("size") / LARGE_BLOCK), F.ceil(F.col("weight") / LARGE_BYTES)).cast("long")
    rows = rows.withColumn("parts", parts).withColumn("part", F.pmod(F.xxhash64("doc_id"), F.col("parts")))
    rows = rows.withColumn("j", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)))
    cell = F.least("part", "j") * F.col("parts") + F.greatest("part", "j")
    rows = rows.select("key", F.shiftleft(F.col("band").cast("long"), 40).bitwiseXOR(cell).alias("at"), "own", "doc_id", "n", "root", "part", "fine")
    return rows.repartition("key", "at").sortWithinPartitions("key", "at").mapInArrow(run, "a long, b long").distinct()


def bounded(pairs: DataFrame, points: DataFrame) -> DataFrame:
    """The pairs (a, b) that the bound by their fine points (a group for each shingle) can't rule out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ok = []
            for n, m, x, y in zip(*(batch.column(i).to_pylist() for i in range(2, 6))):
                x, y = np.frombuffer(x, np.uint8), np.frombuffer(y, np.uint8)
                few = min(len(x), len(y))
                ok.append(7 * int(np.minimum(folded(x, few), folded(y, few)).sum()) >= 3 * (n + m))
            hit = pa.array(ok, pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(hit), batch.column(1).filter(hit)], ["a", "b"])

    left, right = (points.select(F.col("doc_id").alias(c), F.col("n").alias(f"n_{c}"), F.col("fine").alias(f"c_{c}")) for c in "ab")
    sized = pairs.join(left, "a").join(right, "b").where(4 * F.least("n_a", "n_b") >= 3 * F.greatest("n_a", "n_b"))
    return sized.select("a", "b", "n_a", "n_b", "c_a", "c_b").mapInArrow(run, "a long, b long").distinct()


def join_groups(docs: DataFrame, width: int = 5) -> DataFrame:
    """doc_id, n_shingles and component_id (the smallest doc_id reachable by links) of every row."""
    ship(docs.sparkSession)
    spark = docs.sparkSession
    counts, mean = sketch(docs, width)
    release(spark)
    base = cut(described(docs, levels(counts, mean), width))
    full = base.where("n > 0 and doc_id is not null")
    # equal sets: one of them stands for all
    classes = full.groupBy("one", "two", "n").agg(F.min("doc_id").alias("rep"))
    # first shingles that different sets share
    posted = full.select(F.explode("lead").alias("token"), "one")
    shared = cut(posted.groupBy("token").agg(F.min("one").alias("lo"), F.max("one").alias("hi")).where("lo <> hi").select("token"))
    release(spark)
    reps = classes.select(F.col("rep").alias("doc_id")).distinct()
    posted = postings(full, shared).join(reps, "doc_id", "left_semi").distinct().withColumn("own", F.count(F.lit(1)).over(W.partitionBy("doc_id")))
    members = cut(posted.where(F.col("own") >= 1 + F.floor(F.floor((3 * F.col("n") + 3) / 4) / 16)).drop("own"))
    del posted
    release(spark)
    points = full.select("doc_id", "n", "fine")

    # each document against the first one of each of its blocks
    heads = members.groupBy("token").agg(F.min("doc_id").alias("a"))
    tried = members.join(heads, "token").where("doc_id <> a").select("a", F.col("doc_id").alias("b")).distinct()
    edges = verified(docs, bounded(tried, points), width)
    release(spark)
    roots = components(edges)
    release(spark)

    # blocks that still hold several groups, through the tree
    member = members.join(roots, F.col("doc_id") == F.col("node"), "left").select("token", "doc_id", "n", F.coalesce("root", "doc_id").alias("root"))
    sets = member.groupBy("token").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.count(F.lit(1)).alias("size"), F.min("doc_id").alias("first"), F.bit_xor(F.xxhash64("doc_id")).alias("x"), F.bit_xor(F.xxhash64("doc_id", F.lit(1))).alias("y"))
    # the shingles of one passage make blocks of the same documents: one of them is enough; small blocks with the same first document are joined as one
    blocks = sets.where("lo <> hi").groupBy("size", "x", "y").agg(F.min("token").alias("token"), F.min("first").alias("first")).select("token", F.when(F.col("size") > SMALL_BLOCK, F.col("token")).otherwise(F.col("first")).alias("key"))
    held = cut(member.join(blocks, "token").select("key", "doc_id", "n", "root").distinct())
    # what a joined block really holds decides how it is dealt, so that no key is one task's work; few keys hold much
    much = held.groupBy("key").agg(F.count(F.lit(1)).alias("size"), F.sum("n").alias("weight")).where((F.col("size") > SMALL_BLOCK) | (F.col("weight") > LARGE_BYTES))
    held = held.join(much, "key", "left").select("key", F.coalesce("size", F.lit(0)).alias("size"), F.coalesce("weight", F.lit(0)).alias("weight"), "doc_id", "root")
    found = tree_candidates(held.join(points, "doc_id"))
    edges = edges.union(verified(docs, found.join(edges, ["a", "b"], "left_anti"), width))
    release(spark)
    roots = components(edges)
    release(spark)

    by_rep = classes.join(roots, F.col("rep") == F.col("node"), "left").select("one", "two", "n", F.coalesce("root", "rep").alias("root"))
    rows = base.select("doc_id", "n", "one", "two").join(by_rep, ["one", "two", "n"], "left")
    return rows.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.coalesce("root", "doc_id")).alias("component_id"))


def one_of_each(docs: DataFrame, width: int = 5) -> DataFrame:
    """docs with one document of each group, that of the smallest doc_id; rows without a doc_id stay."""
    first = join_groups(docs, width).where(F.col("doc_id") == F.col("component_id")).select("doc_id").distinct()
    kept = docs.where(F.col("doc_id").isNotNull()).join(first, "doc_id", "left_semi")
    turn, name = F.row_number().over(W.partitionBy("doc_id").orderBy(F.xxhash64("text"))), fresh("turn", docs.columns)
    kept = kept.withColumn(name, turn).where(F.col(name) == 1).select(*docs.columns)
    return kept.unionByName(docs.where(F.col("doc_id").isNull()))
