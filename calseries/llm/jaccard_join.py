"""Size-aware heavy-light join: near duplicates by Jaccard similarity of word shingles, exactly.

Sets of at most ``boundary`` shingles are light: they enumerate all their subsets of the sizes that a link needs, and
two light sets link exactly when they share such a subset. Larger sets are heavy: their rarest shingles (the shortest
prefix that two linked sets must share) go to inverted lists, which light sets near the boundary probe too. The
boundary is where the estimated cost of both is least, from the counts of sets by size.

Neither side emits all pairs of a list or of equal subsets. Lists are chained in order of size, which connects every
pair that could link; the components of the chains are clusters. In a large corpus single shingles chain unlike texts
into clusters without end, so clusters of more than one block are chained anew by equal parts of sets, which hold several
shingles each, and fall into those that are alike. The exact intersections inside a cluster are counted block by block in
one matrix product per pair of blocks. Only a spanning forest of the links leaves a block.
Rows with the same set are one class, known by the set's own 64-bit fingerprint all through, so that ids may repeat.
How rare a shingle is comes from a count sketch over all texts; any order of shingles gives the same links, a good one
gives short lists. Classes and components of very many rows are joined by broadcast, which their share bounds.

Defined cases: null and empty texts have empty sets and link with nothing; a row with a null id keeps its n_shingles,
has itself no part in links, and its component_id is that of its equals, or null; rows that repeat an id and text are one
document; rows with the same id and different texts are documents of their own, with their own links and components.
"""

from __future__ import annotations

import itertools
import math
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import WORD, forget, fresh, release, staged, table, travels
from .graph import HOT, components, least
from .textkit import BASE, LOWER, SPACE, U, Slab, distinct_by_text, hash_runs, mix, runs, slabs, windows

travels(__name__)

SHINGLE = 4
PERCENT = 85
#: Slots of the count sketch, and how many of them travel in one row.
SKETCH = 1 << 22
SKETCH_ROW = 1 << 16
#: Largest boundary whose cost is worked out: a set of that size has 36,000 subsets, so that lists are far cheaper.
MOST_LIGHT = 32
#: What a posting in an inverted list costs against an enumerated subset: it may bring the text to a cluster.
POSTING_COST = 12
#: Shingles in a block, where each set counts ``BLOCK_SET`` more.
BLOCK, BLOCK_SET = 800_000, 300
#: Most sizes of large clusters (24 bytes each) that are broadcast; more are joined by a shuffle.
MOST_SIZES = 500_000
KEY_BITS = 48
#: Shingles that a part of a set must hold to be posted by itself, if so many parts of every set do.
FULL = 2
#: Bits of the filter that keeps most texts outside clusters from travelling, and bits that each id sets.
FILTER, FILTER_HASHES = 1 << 25, 3


def sets(slab: Slab, k: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """The distinct shingle hashes (54 bits) of each text, ascending, and their texts."""
    buf = LOWER[slab.buf]
    s, e, t = runs(~SPACE[buf], slab.off)
    h = hash_runs(buf, s, e)
    win, at = windows(h, t, k)
    owner = t[at]
    words = np.bincount(t, minlength=len(slab))
    short = np.flatnonzero((words > 0) & (words < k))
    if len(short):
        first = np.searchsorted(t, short)
        whole = np.zeros(len(short), U)
        for i, (a, n) in enumerate(zip(first.tolist(), words[short].tolist(), strict=True)):
            x = np.array([n], U)
            for v in h[a : a + n]:
                x = mix(x * U(0x9E3779B97F4A7C15) + v)
            whole[i] = x[0]
        win, owner = np.r_[win, mix(whole + U(1))], np.r_[owner, short]
    return distinct_by_text(win, owner)


def needed(s: int, t: int, percent: int = PERCENT) -> int:
    """The least intersection with which sets of these sizes link."""
    return -(-percent * (s + t) // (100 + percent))


def prefix_length(n, percent: int = PERCENT):
    return n - (-(-percent * n // 100)) + 1


def subset_sizes(s: int, boundary: int, percent: int = PERCENT) -> list[int]:
    """The subset sizes that a light set of size ``s`` enumerates."""
    found = {needed(s, t, percent) for t in range(1, boundary + 1)}
    return sorted(c for c in found if c <= s and any(needed(s, t, percent) == c <= min(s, t) for t in range(1, boundary + 1)))


def choose_boundary(count_by_size: dict[int, int], percent: int = PERCENT) -> int:
    """The boundary of least cost, from the number of sets of each size up to some above ``MOST_LIGHT``."""

    def cost(x: int) -> float:
        total = 0.0
        for s, n in count_by_size.items():
            if s <= x:
                total += n * sum(math.comb(s, c) for c in subset_sizes(s, x, percent))
            if s > x or 100 * s >= percent * (x + 1):
                total += n * POSTING_COST * prefix_length(s, percent)
        return total

    return min(range(1, MOST_LIGHT + 1), key=lambda x: (cost(x), x))


def text_hash(text: str = "text") -> Column:
    return F.xxhash64(F.col(text).cast("string"))


def fingerprints(docs: DataFrame, k: int = SHINGLE) -> DataFrame:
    """One row per document (doc_id, n, f1, f2, and th, a hash of its text), and each task's part of the count sketch
    (block, counts)."""

    def work(batches):
        counts = np.zeros(SKETCH, np.int32)
        names = ["doc_id", "th", "n", "f1", "f2", "block", "counts"]
        for b in batches:
            for slab in slabs(b.column(2)):
                h, owner = sets(slab, k)
                m = len(slab)
                cut = np.searchsorted(owner, np.arange(m + 1))
                n = np.diff(cut)
                c1, c2 = np.zeros(len(h) + 1, U), np.zeros(len(h) + 1, U)
                np.cumsum(mix(h + U(1)), out=c1[1:])
                np.cumsum(mix(h ^ U(0x5851F42D4C957F2D)), out=c2[1:])
                f1, f2 = (c[cut[1:]] - c[cut[:-1]] for c in (c1, c2))
                slots, times = np.unique((h & U(SKETCH - 1)).astype(np.int64), return_counts=True)
                counts[slots] += times
                yield pa.RecordBatch.from_arrays([b.column(0).slice(slab.lo, m), b.column(1).slice(slab.lo, m), pa.array(n.astype(np.int32)), pa.array(f1.view(np.int64)), pa.array(f2.view(np.int64)), pa.nulls(m, pa.int32()), pa.nulls(m, pa.binary())], names)
        for block in range(SKETCH // SKETCH_ROW):
            part = counts[block * SKETCH_ROW : (block + 1) * SKETCH_ROW]
            if part.any():
                packed = zlib.compress(part.astype("<i4").view(np.uint8).reshape(-1, 4).T.tobytes(), 1)
                yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.nulls(1, pa.int64()), pa.nulls(1, pa.int32()), pa.nulls(1, pa.int64()), pa.nulls(1, pa.int64()), pa.array([block], pa.int32()), pa.array([packed], pa.binary())], names)

    schema = "doc_id long, th long, n int, f1 long, f2 long, block int, counts binary"
    return docs.select(F.col("doc_id").cast("long"), text_hash().alias("th"), F.col("text").cast("string")).mapInArrow(work, schema)


def rarity(prints: DataFrame) -> np.ndarray:
    """A level from 0 to 63 for each slot of the sketch, higher for shingles in more documents; 4 MB."""
    blocks = SKETCH // SKETCH_ROW

    def add_up(batches):
        total: dict[int, np.ndarray] = {}
        for b in batches:
            for block, packed in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                part = np.frombuffer(zlib.decompress(packed), np.uint8).reshape(4, -1).T.copy().view("<i4").ravel()
                total[block] = total.get(block, 0) + part.astype(np.int64)
        for block, x in total.items():
            level = np.minimum(63, np.floor(2 * np.log2(np.maximum(x, 1)))).astype(np.uint8)
            yield pa.RecordBatch.from_arrays([pa.array([block], pa.int32()), pa.array([level.tobytes()], pa.binary())], ["block", "level"])

    parts = prints.where("kind = 1").select("block", "counts").repartition(blocks, "block")
    out = np.zeros(SKETCH, np.uint8)
    for r in parts.mapInArrow(add_up, "block int, level binary").collect():
        out[r["block"] * SKETCH_ROW : (r["block"] + 1) * SKETCH_ROW] = np.frombuffer(r["level"], np.uint8)
    return out


def postings(docs: DataFrame, levels: np.ndarray, boundary: int, k: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """(key, c, f1, n): with c = 0 the prefix shingles of a set, with c > 0 the hashes of its subsets of size c."""
    kept = docs.sparkSession.sparkContext.broadcast(levels)
    sizes = {s: subset_sizes(s, boundary, percent) for s in range(1, boundary + 1)}
    probe_from = -(-percent * (boundary + 1) // 100)
    low = U((1 << KEY_BITS) - 1)

    def work(batches):
        level, seen = kept.value, set()
        for b in batches:
            for slab in slabs(b.column(0)):
                h, owner = sets(slab, k)
                m = len(slab)
                cut = np.searchsorted(owner, np.arange(m + 1))
                n = np.diff(cut)
                c1 = np.zeros(len(h) + 1, U)
                np.cumsum(mix(h + U(1)), out=c1[1:])
                f1 = (c1[cut[1:]] - c1[cut[:-1]]).view(np.int64)
                new = n > 0  # this task posts equal sets once
                for i, f in enumerate(f1.tolist()):
                    if f in seen:
                        new[i] = False
                    else:
                        seen.add(f)
                key = np.sort((owner.astype(U) << U(54)) | (level[(h & U(SKETCH - 1)).astype(np.int64)].astype(U) << U(KEY_BITS)) | (h >> U(54 - KEY_BITS)))
                place = np.arange(len(key)) - cut[owner]
                take = (place < prefix_length(n, percent)[owner]) & new[owner] & (n[owner] >= probe_from)
                keys, cs, who = [(key[take] & low).astype(np.int64)], [np.zeros(int(take.sum()), np.int32)], [owner[take]]
                for i in np.flatnonzero(new & (n <= boundary)).tolist():
                    terms = mix(h[cut[i] : cut[i + 1]] + U(1)).tolist()
                    for c in sizes[int(n[i])]:
                        drops = [sum(d) for d in itertools.combinations(terms, len(terms) - c)]
                        whole = sum(terms)
                        keys.append(np.array([(whole - d) & 0x7FFFFFFFFFFFFFFF for d in drops], np.int64))
                        cs.append(np.full(len(drops), c, np.int32))
                        who.append(np.full(len(drops), i))
                who = np.concatenate(who)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys)), pa.array(np.concatenate(cs)), pa.array(f1[who]), pa.array(n[who].astype(np.int32))], ["key", "c", "f1", "n"])

    return docs.select(F.col("text").cast("string")).mapInArrow(work, "key long, c int, f1 long, n int")


def chains(posted: DataFrame, percent: int = PERCENT) -> DataFrame:
    """Candidate edges between sets: a list's neighbours in order of size, an equal subset's holders to its smallest."""
    w = Window.partitionBy("key", "c").orderBy("n", "f1")
    light = F.col("c") > 0
    other = F.when(light, F.struct(F.first("f1").over(w), F.first("n").over(w))).otherwise(F.struct(F.lag("f1").over(w), F.lag("n").over(w)))
    e = posted.withColumn("o", other).select(F.col("f1").alias("a"), F.col("o.col1").alias("b"), "n", F.col("o.col2").alias("m"), "c")
    fits = F.when(F.col("c") > 0, 100 * F.col("c") >= percent * (F.col("n") + F.col("m") - F.col("c"))).otherwise(100 * F.col("m") >= percent * F.col("n"))
    return e.where(F.col("b").isNotNull() & (F.col("a") != F.col("b")) & fits).select("a", "b")


def size_groups(most: int, percent: int = PERCENT) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The largest size of each group up to one above ``most``, the number of parts, the shingles that make a part full,
    and the parts of a set that needn't be full.

    Sets that link are in one group or in neighbouring ones. They differ in H shingles at most, so of H + 1 + t parts
    t + 1 are equal, and one of these is full unless more than t parts of both sets are not."""
    top = [0]
    while top[-1] <= most:
        top.append(max(top[-1] + 1, 100 * top[-1] // percent))
    top.append(max(top[-1] + 1, 100 * top[-1] // percent))
    parts, full, spare = [], [], []
    for below, r in zip(top[:-1], top[1:], strict=True):
        least, need = -(-percent * (below + 1) // 100), 2 * r * (100 - percent) // (100 + percent) + 1
        found = (need, 1, 0)  # too small for spare parts
        for size in range(FULL, 0, -1):
            t = 0
            while t <= need // 2:
                x = least / (need + t)
                seldom = (need + t) * math.exp(-x) * sum(x**k / math.factorial(k) for k in range(size))
                if seldom + 3 * math.sqrt(seldom) <= t:
                    break
                t += 1
            if t <= need // 2:
                found = (need + t, size, t)
                break
        parts.append(found[0])
        full.append(found[1])
        spare.append(found[2])
    return tuple(np.array(x) for x in (top[1:], parts, full, spare))


def signatures(docs: DataFrame, members: DataFrame, levels: np.ndarray, k: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """(key, c, f1, n) with c = 0: the full parts of each member's set, in its group of sizes and the next if a link leads
    there; with c = -1 the prefix shingles of the sets of which too many parts are not full."""
    kept = docs.sparkSession.sparkContext.broadcast(levels)
    low = U((1 << KEY_BITS) - 1)

    def work(batches):
        level, seen = kept.value, set()
        for b in batches:
            for slab in slabs(b.column(1)):
                h, owner = sets(slab, k)
                m = len(slab)
                cut = np.searchsorted(owner, np.arange(m + 1))
                n = np.diff(cut)
                x = mix(h + U(1))
                c1 = np.zeros(len(h) + 1, U)
                np.cumsum(x, out=c1[1:])
                f1 = (c1[cut[1:]] - c1[cut[:-1]]).view(np.int64)
                new = n > 0
                for i, f in enumerate(f1.tolist()):
                    new[i] &= f not in seen
                    seen.add(f)
                top, parts, full, spare = size_groups(int(n.max(initial=1)), percent)
                keys, cs, who, odd = [], [], [], np.zeros(m, bool)
                own = np.searchsorted(top, n)
                for step in (0, 1):
                    g = own + step
                    here = new & ((step == 0) | (100 * n // percent > top[own]))
                    start = np.zeros(m + 1, np.int64)
                    np.cumsum(np.where(here, parts[g], 0), out=start[1:])
                    in_ = here[owner]
                    slot = start[owner[in_]] + (mix(h[in_] ^ U(0x2545F4914F6CDD1D)) % parts[g][owner[in_]].astype(U)).astype(np.int64)
                    order = np.argsort(slot, kind="stable")
                    edge = np.searchsorted(slot[order], np.arange(start[-1] + 1))
                    total = np.zeros(len(order) + 1, U)
                    np.cumsum(x[in_][order], out=total[1:])
                    text = np.repeat(np.arange(m), np.diff(start))
                    ok = np.diff(edge) >= full[g][text]
                    odd |= here & (np.bincount(text[~ok], minlength=m) > spare[g])
                    place = np.arange(start[-1]) - start[text]
                    sums = total[edge[1:]] - total[edge[:-1]]
                    key = mix(mix(sums + U(BASE) * (g[text] + 1).astype(U)) + place.astype(U))
                    keys.append((key[ok] >> U(1)).astype(np.int64))
                    who.append(text[ok])
                    cs.append(np.zeros(int(ok.sum()), np.int32))
                rare = np.sort((owner.astype(U) << U(54)) | (level[(h & U(SKETCH - 1)).astype(np.int64)].astype(U) << U(KEY_BITS)) | (h >> U(54 - KEY_BITS)))
                take = (np.arange(len(rare)) - cut[owner] < prefix_length(n, percent)[owner]) & odd[owner]
                keys.append((rare[take] & low).astype(np.int64))
                who.append(owner[take])
                cs.append(np.full(int(take.sum()), -1, np.int32))
                who = np.concatenate(who)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys)), pa.array(np.concatenate(cs)), pa.array(f1[who]), pa.array(n[who].astype(np.int32))], ["key", "c", "f1", "n"])

    return only_members(docs, members, packed=False).mapInArrow(work, "key long, c int, f1 long, n int")


def parted(docs: DataFrame, members: DataFrame, levels: np.ndarray, k: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """``members`` with the clusters of more than one block replaced by those that equal parts of sets chain; a member
    that no link can lead to is left out."""
    weights = members.groupBy("cluster").agg(F.sum(F.col("n") + BLOCK_SET).alias("weight"))
    large = staged(weights.where(F.col("weight") > BLOCK).select("cluster"), "large")
    count = large.count()
    if not count:
        return members
    named = F.broadcast(large) if count <= MOST_SIZES else large
    again = staged(members.join(named, "cluster", "left_semi").select("rep", "f1", "n"), "again")
    chained = with_roots(chains(signatures(docs, again, levels, k, percent), percent))
    smaller = again.join(chained, F.col("f1") == F.col("node")).select("rep", "f1", "n", F.col("root").alias("cluster"))
    return staged(members.join(named, "cluster", "left_anti").select(*smaller.columns).unionByName(smaller), "parted")


def links(values: list[np.ndarray], side: np.ndarray, percent: int = PERCENT) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (i, j) of the given sets that link; with two sides, pairs across them only."""
    m = len(values)
    n = np.array([len(v) for v in values])
    if m == 2:
        o = len(np.intersect1d(values[0], values[1], assume_unique=True))
        ok = 100 * o >= percent * (n[0] + n[1] - o)
        return (np.array([0]), np.array([1])) if ok else (np.zeros(0, int), np.zeros(0, int))
    owner = np.repeat(np.arange(m), n)
    uniq, col, df = np.unique(np.concatenate(values), return_inverse=True, return_counts=True)
    shared = df[col] > 1
    owner, col = owner[shared], col[shared]
    names = np.unique(col)
    col = np.searchsorted(names, col)
    left, right = (np.flatnonzero(side == s) for s in (0, 1)) if side.any() else (np.arange(m), np.arange(m))
    both = np.zeros((len(left), len(right)), np.float32)
    width = max(256, (1 << 23) // m)
    order = np.argsort(col, kind="stable")
    owner, col = owner[order], col[order]
    for lo in range(0, len(names), width):
        a, b = np.searchsorted(col, (lo, lo + width))
        grid = np.zeros((m, min(width, len(names) - lo)), np.float32)
        grid[owner[a:b], col[a:b] - lo] = 1
        both += grid[left] @ grid[right].T
    i, j = np.nonzero(100 * both >= percent * (n[left][:, None] + n[right][None, :] - both))
    i, j = left[i], right[j]
    keep = i < j if not side.any() else i != j
    return i[keep], j[keep]


def forest(m: int, i: np.ndarray, j: np.ndarray) -> list[tuple[int, int]]:
    """Edges that connect what the pairs connect, at most ``m - 1``."""
    root = list(range(m))

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    out = []
    for a, b in zip(i.tolist(), j.tolist(), strict=True):
        ra, rb = find(a), find(b)
        if ra != rb:
            root[max(ra, rb)] = min(ra, rb)
            out.append((a, b))
    return out


def _bits(ids: np.ndarray) -> np.ndarray:
    """The filter's bits that these ids set, one row an id."""
    x = mix(ids.view(U))
    return np.stack([(mix(x + U(k)) % U(FILTER)).astype(np.int64) for k in range(FILTER_HASHES)], 1)


def only_members(docs: DataFrame, members: DataFrame, packed: bool = True) -> DataFrame:
    """(doc_id, packed) of the rows whose id may be a member's, so that few texts travel, compressed, to the join that
    decides; or (doc_id, text) of them.

    The ids go into a filter of FILTER bits, whatever their number: too many let more rows pass, none is lost."""

    def collect(batches):
        found = np.zeros(FILTER, bool)
        for b in batches:
            found[_bits(b.column(0).to_numpy()).ravel()] = True
        if found.any():
            yield pa.RecordBatch.from_arrays([pa.array([0], pa.int32()), pa.array([zlib.compress(np.packbits(found).tobytes(), 1)], pa.binary())], ["one", "bits"])

    def merge(batches):
        bits = np.zeros(FILTER // 8, np.uint8)
        for b in batches:
            for x in b.column(1).to_pylist():
                bits |= np.frombuffer(zlib.decompress(x), np.uint8)
        if bits.any():
            yield pa.RecordBatch.from_arrays([pa.array([0], pa.int32()), pa.array([zlib.compress(bits.tobytes(), 1)], pa.binary())], ["one", "bits"])

    schema = "one int, bits binary"
    merged = members.select("rep").mapInArrow(collect, schema).repartition(1, "one").mapInArrow(merge, schema)
    bits = np.zeros(FILTER // 8, np.uint8)
    for r in merged.collect():  # one row of FILTER bits
        bits |= np.frombuffer(zlib.decompress(r["bits"]), np.uint8)
    kept = docs.sparkSession.sparkContext.broadcast(bits)

    def sieve(batches):
        there, seen = np.unpackbits(kept.value).view(bool), set()
        for b in batches:
            b = b.filter(b.column(0).is_valid())
            b = b.filter(pa.array(there[_bits(b.column(0).to_numpy())].all(1)))
            new = []  # rows that repeat an id and text travel once a task
            for row in zip(b.column(0).to_pylist(), b.column(2).to_pylist(), strict=True):
                new.append(row not in seen)
                seen.add(row)
            b = b.filter(pa.array(new, pa.bool_()))
            if packed:
                texts = pa.array([zlib.compress((x or "").encode(), 6) for x in b.column(1).to_pylist()], pa.binary())
            else:
                texts = b.column(1)
            yield pa.RecordBatch.from_arrays([b.column(0), texts], [b.schema.names[0], "packed" if packed else "text"])

    schema = "doc_id long, packed binary" if packed else "doc_id long, text string"
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), text_hash().alias("th")).mapInArrow(sieve, schema)


def unpacked(column: pa.Array, most: int = 200):
    """Slabs of compressed texts, a few at a time."""
    for lo in range(0, len(column), most):
        texts = pa.array([zlib.decompress(x).decode() for x in column.slice(lo, most).to_pylist()], pa.large_string())
        for slab in slabs(texts):
            slab.lo += lo
            yield slab


def verified(docs: DataFrame, members: DataFrame, k: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """Edges (a, b) between the fingerprints of classes that connect what the links inside each cluster connect.

    ``members``: f1, rep (an id whose text has that set), n, cluster."""
    # a cluster's members lie in order of size; of one size, in the order of a hash: a place is known without a sort
    sizes = members.groupBy("cluster", "n").agg((F.count(F.lit(1)) * (F.col("n") + BLOCK_SET)).alias("weight"))
    by_size = Window.partitionBy("cluster").orderBy("n")
    sizes = sizes.withColumn("before", F.sum("weight").over(by_size) - F.col("weight")).withColumn("total", F.sum("weight").over(Window.partitionBy("cluster")))
    large = staged(sizes.where(F.col("total") > BLOCK).drop("total"), "sizes")  # other clusters are one block
    share = F.pmod(F.xxhash64("f1"), F.lit(1 << 20)) / F.lit(float(1 << 20))
    placed = members.join(F.broadcast(large) if large.count() <= MOST_SIZES else large, ["cluster", "n"], "left")
    placed = placed.withColumn("blk", F.coalesce(F.floor((F.col("before") + F.col("weight") * share) / BLOCK), F.lit(0)).cast("int")).drop("before", "weight")
    blocks = placed.groupBy("cluster", "blk").agg(F.min("n").alias("lo"), F.max("n").alias("hi"))
    x, y = blocks.alias("x"), blocks.alias("y")
    pairs = x.join(y, (F.col("x.cluster") == F.col("y.cluster")) & (F.col("x.blk") <= F.col("y.blk")) & (100 * F.col("x.hi") >= percent * F.col("y.lo")))
    pairs = pairs.select(F.col("x.cluster").alias("cluster"), F.col("x.blk").alias("i"), F.col("y.blk").alias("j"))
    roles = pairs.select("cluster", F.explode(F.array_distinct(F.array("i", "j"))).alias("blk"), "i", "j")
    roles = roles.groupBy("cluster", "blk").agg(F.collect_list(F.struct("i", "j")).alias("where"))
    placed = placed.join(roles, ["cluster", "blk"]).select("rep", "f1", "cluster", "blk", "where")

    texts = only_members(docs, members).select(F.col("doc_id").alias("rep"), "packed")
    spread = texts.join(placed, "rep").select("f1", "cluster", "blk", F.inline("where"), "packed")
    spread = spread.repartition("cluster", "i", "j").sortWithinPartitions("cluster", "i", "j", "f1")

    def settle(key, f1s, blks, hs):
        f1s, where = np.unique(np.array(f1s, np.int64), return_index=True)
        if len(f1s) < 2:
            return []
        values = [hs[t] for t in where.tolist()]
        side = (np.array(blks)[where] != key[1]).astype(int)
        return [(int(f1s[a]), int(f1s[b])) for a, b in forest(len(f1s), *links(values, side, percent))]

    def work(batches):
        key, f1s, blks, hs = None, [], [], []

        def edges(out):
            return pa.RecordBatch.from_arrays([pa.array([e[k] for e in out], pa.int64()) for k in (0, 1)], ["a", "b"])

        for b in batches:
            out = []
            f1, cluster, blk, i, j = (b.column(c).to_pylist() for c in range(5))
            for slab in unpacked(b.column(5)):
                h, owner = sets(slab, k)
                cut = np.searchsorted(owner, np.arange(len(slab) + 1))
                c1 = np.zeros(len(h) + 1, U)
                np.cumsum(mix(h + U(1)), out=c1[1:])
                got = (c1[cut[1:]] - c1[cut[:-1]]).view(np.int64).tolist()
                for n in range(len(slab)):
                    r = slab.lo + n
                    if (cluster[r], i[r], j[r]) != key:
                        if len(f1s) > 1:
                            out += settle(key, f1s, blks, hs)
                        key, f1s, blks, hs = (cluster[r], i[r], j[r]), [], [], []
                    if got[n] == f1[r] and (not f1s or f1s[-1] != f1[r]):  # another text of the same id has another set
                        f1s.append(f1[r])
                        blks.append(blk[r])
                        hs.append(h[cut[n] : cut[n + 1]].copy())
            yield edges(out)
        yield edges(settle(key, f1s, blks, hs) if len(f1s) > 1 else [])

    return spread.select("f1", "cluster", "blk", "i", "j", "packed").mapInArrow(work, "a long, b long")


def with_roots(edges: DataFrame) -> DataFrame:
    """(node, root) of the components, the roots themselves included."""
    found = components(edges)
    return found.unionAll(found.select(F.col("root").alias("node"), "root").distinct())


def classes_of(docs: DataFrame, k: int = SHINGLE, percent: int = PERCENT) -> tuple[DataFrame, DataFrame]:
    """The rows (doc_id, th, n, f1, f2), and their classes: f1, f2, n, times and ``first``, the (doc_id, th) that is least
    in the whole component. Classes whose rows have null ids only have no ``first``."""
    prints = staged(fingerprints(docs, k).withColumn("kind", F.col("block").isNotNull().cast("int")), "prints", "kind")
    rows = prints.where("kind = 0").select("doc_id", "th", "n", "f1", "f2")
    by_size = {r["n"]: r["count"] for r in rows.where(F.col("n").between(1, 2 * MOST_LIGHT)).groupBy("n").count().collect()}
    boundary = choose_boundary(by_size, percent)
    levels = rarity(prints)
    forget(prints, "kind=1")
    clusters = with_roots(chains(postings(docs, levels, boundary, k, percent), percent))
    own = F.min(F.when(F.col("doc_id").isNotNull(), F.struct("doc_id", "th"))).alias("own")
    classes = staged(rows.where("n > 0").groupBy("f1", "f2", "n").agg(own, F.count(F.lit(1)).alias("times")), "classes")
    members = classes.where(F.col("own").isNotNull()).join(clusters, F.col("f1") == F.col("node"))
    members = staged(members.select(F.col("own.doc_id").alias("rep"), "f1", "n", F.col("root").alias("cluster")), "members")
    release(docs.sparkSession)
    members = parted(docs, members, levels, k, percent)
    release(docs.sparkSession)
    linked = staged(classes.join(with_roots(verified(docs, members, k, percent)), F.col("f1") == F.col("node")).drop("node"), "linked")
    firsts = least(linked, "root", linked.select(F.col("root").alias("u"), F.col("own").alias("v")), linked.count())
    named = classes.join(firsts.select(F.col("f1").alias("g1"), F.col("f2").alias("g2"), F.col("n").alias("gn"), "m"), (F.col("f1") == F.col("g1")) & (F.col("f2") == F.col("g2")) & (F.col("n") == F.col("gn")), "left")
    return rows, named.select("f1", "f2", "n", "times", F.coalesce("m", "own").alias("first"))


def near_duplicates(docs: DataFrame, k: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """doc_id, n_shingles, component_id for every row of ``docs`` (doc_id, text)."""
    rows, classes = classes_of(docs, k, percent)
    # a class of more than one in HOT of all rows is told by broadcast: there are fewer than HOT of them
    key, share = ["f1", "f2", "n"], F.col("times") * HOT
    total = rows.count()
    named = staged(classes.select(*key, "times", F.col("first.doc_id").alias("component_id")), "named")
    hot = named.where(share > total).select(*key, "component_id", F.lit(True).alias("hot"))
    told = rows.join(F.broadcast(hot), key, "left")
    cold = told.where(F.col("hot").isNull()).drop("component_id").join(named.where(share <= total).select(*key, "component_id"), key, "left")
    out = told.where(F.col("hot")).unionByName(cold.select(*told.columns))
    return out.select("doc_id", F.col("n").cast("long").alias("n_shingles"), F.when(F.col("n") == 0, F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"))


def keep_one(docs: DataFrame, k: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """The rows of ``docs`` whose (id, text) is the least of their component, each once; rows with a null id or without a
    word, which link with nothing, stay as they are."""
    _, classes = classes_of(docs, k, percent)
    id_, th = fresh(docs, "kept_id", "kept_text")
    firsts = classes.where(F.col("first").isNotNull()).select(F.col("first.doc_id").alias(id_), F.col("first.th").alias(th)).distinct()
    apart = F.col("doc_id").isNull() | ~F.coalesce(F.col("text").cast("string").rlike(WORD), F.lit(False))
    # equal rows become one before they travel
    once = docs.where(~apart).withColumn(id_, F.col("doc_id").cast("long")).withColumn(th, text_hash()).dropDuplicates([id_, th])
    return once.join(firsts, [id_, th], "left_semi").select(*docs.columns).unionAll(docs.where(apart))


def op7_heavy_light_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
