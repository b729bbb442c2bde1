"""SimHash near-duplicates with a Gray-order hierarchical index.

A text's fingerprint takes the majority of each bit over the hashes of its word shingles. Distinct fingerprints are dealt to
cells by pigeonhole: of four 16-bit blocks two must be whole when two bits differ, so each fingerprint stands in six cells
named by two blocks; a cell above `split` rows is dealt again by its other 32 bits, which leaves 16 free bits, so no cell
outgrows 65,536 rows. In a cell, fingerprints are sorted by Gray rank; upper nodes hold the bit pattern that all below
share, a query adds up its differences node by node and leaves a whole group as soon as they exceed the radius. Cells give
a spanning forest, never all pairs; the forests are joined by `components`.

Null and empty texts have fingerprint zero and are linked like any other. Repeated rows share a component. Empty tables
give empty results. Extra columns are ignored.
"""
from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bytescan import mix
from .common import components, documents, settle, text_view

PAIRS = [(0, 1), (0, 2), (0, 3), (1, 2), (1, 3), (2, 3)]
_BITS = ((np.arange(256)[:, None] >> np.arange(8)) & 1).astype(np.int64)


def shingle_hashes(raw: bytes, width: int, seed: int) -> list[int]:
    words = raw.lower().split()  # bytes: only A-Z changes, only ASCII white space separates
    if not words:
        return []
    joined = b" ".join(words)
    if len(words) <= width:
        return [xxhash.xxh64_intdigest(joined, seed)]
    size = np.fromiter(map(len, words), np.int64, len(words))
    end = np.cumsum(size + 1) - 1
    digest = xxhash.xxh64_intdigest
    return [digest(joined[a:b], seed) for a, b in zip((end - size)[: len(words) - width + 1].tolist(), end[width - 1 :].tolist(), strict=True)]


def fingerprint_of(texts: list[bytes], width: int, seed: int) -> np.ndarray:
    """Fingerprints as uint64."""
    return majority([np.array(shingle_hashes(t, width, seed), np.uint64) for t in texts])


def majority(each: list[np.ndarray]) -> np.ndarray:
    """The majority of each bit over the hashes of each text, as uint64."""
    n = np.array([len(h) for h in each])
    flat = np.concatenate([*each, np.zeros(0, np.uint64)])
    key = flat.view(np.uint8).reshape(-1, 8).astype(np.int64) + np.arange(8) * 256 + np.repeat(np.arange(len(each)), n)[:, None] * 2048
    count = np.bincount(key.ravel(), minlength=len(each) * 2048).reshape(len(each), 8, 256) @ _BITS
    bits = (2 * count.reshape(len(each), 64) > n[:, None]).astype(np.uint8)
    return np.packbits(bits, axis=1, bitorder="little").view(np.uint64).ravel()


def fingerprints(docs: DataFrame, width: int = 5, seed: int = 42) -> DataFrame:
    """(doc_id, fp): fp as a signed long."""

    def run(batches):
        for b in batches:
            data, offs = text_view(b.column(1))
            raw, n = data.tobytes(), len(offs) - 1
            out, lo = np.zeros(n, np.uint64), 0
            while lo < n:
                hi = lo + 1
                while hi < n and hi - lo < 64 and offs[hi + 1] - offs[lo] < 1 << 19:
                    hi += 1
                out[lo:hi] = fingerprint_of([raw[offs[i] : offs[i + 1]] for i in range(lo, hi)], width, seed)
                lo = hi
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out.view(np.int64))], names=["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, fp long")


# -- the index ----------------------------------------------------------------------------------------------------------


def gray_rank(x: np.ndarray) -> np.ndarray:
    """The place of a code word in reflected Gray order."""
    for s in (1, 2, 4, 8, 16, 32):
        x = x ^ (x >> np.uint64(s))
    return x


class GrayIndex:
    """Sorted fingerprints of one or more cells under a binary hierarchy of shared bit patterns."""

    LEAF = 4

    def __init__(self, x: np.ndarray, cell: np.ndarray):
        order = np.lexsort((gray_rank(x), cell))
        self.order, self.x, cell = order, x[order], cell[order]
        first = np.flatnonzero(np.append(True, cell[1:] != cell[:-1]))
        self.root = np.repeat(np.arange(len(first)), np.diff(np.append(first, len(x))))
        lo, hi = first, np.append(first[1:], len(x))
        base_mask = np.zeros(len(lo), np.uint64)
        self.levels = []
        while True:
            value = self.x[lo]
            mask = ~self._spread(lo, hi)
            big = hi - lo > self.LEAF
            child = np.full(len(lo), -1)
            child[big] = np.arange(int(big.sum())) * 2
            self.levels.append((lo, hi, value, mask & ~base_mask, child))
            if not big.any():
                break
            mid = (lo[big] + hi[big]) // 2
            lo, hi = np.stack([lo[big], mid], 1).ravel(), np.stack([mid, hi[big]], 1).ravel()
            base_mask = np.repeat(mask[big], 2)

    def _spread(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """Bits in which the rows of each node differ."""
        step = np.zeros(len(self.x), np.uint64)
        step[1:] = self.x[1:] ^ self.x[:-1]
        size = hi - lo
        ends = np.cumsum(size)
        at = np.repeat(lo - (ends - size), size) + np.arange(int(ends[-1]))
        part = step[at]
        part[ends - size] = 0  # the first row of a node differs from nothing
        return np.bitwise_or.reduceat(part, ends - size)

    def links(self, radius: int):
        """Arrays (i, j) of places in x, i before j in Gray order, at most radius bits apart; batch by batch."""
        n, step = len(self.x), 4096
        for start in range(0, n, step):
            q = np.arange(start, min(n, start + step))
            node, acc = self.root[q], np.zeros(len(q), np.int64)
            for lo, hi, value, mask, child in self.levels:
                acc = acc + np.bitwise_count((self.x[q] ^ value[node]) & mask[node])
                keep = (acc <= radius) & (hi[node] > q + 1)
                q, node, acc = q[keep], node[keep], acc[keep]
                leaf = child[node] < 0
                if leaf.any():
                    ql, nl = q[leaf], node[leaf]
                    for k in range(self.LEAF):
                        j = lo[nl] + k
                        ok = (j < hi[nl]) & (j > ql)
                        a, b = ql[ok], j[ok]
                        near = np.bitwise_count(self.x[a] ^ self.x[b]) <= radius
                        if near.any():
                            yield self.order[a[near]], self.order[b[near]]
                q, c, acc = q[~leaf], child[node[~leaf]], acc[~leaf]
                q, node, acc = np.repeat(q, 2), np.stack([c, c + 1], 1).ravel(), np.repeat(acc, 2)


def forest(n: int, pairs) -> np.ndarray:
    """The least place reachable from each place."""
    top = np.arange(n)
    for a, b in pairs:
        while True:
            ra, rb = top[a], top[b]
            while (top[ra] != ra).any():
                ra = top[ra]
            while (top[rb] != rb).any():
                rb = top[rb]
            lo, hi = np.minimum(ra, rb), np.maximum(ra, rb)
            open_ = lo != hi
            if not open_.any():
                break
            np.minimum.at(top, hi[open_], lo[open_])
    while (top[top] != top).any():
        top = top[top]
    return top


def _cells(radius: int, rows: int = 1 << 16):
    """Streams rows sorted by cell; whole cells are indexed together, some ten thousand rows at a time."""

    def solve(cell: np.ndarray, fp: np.ndarray):
        top = forest(len(fp), GrayIndex(fp.view(np.uint64), cell).links(radius))
        at = np.flatnonzero(top != np.arange(len(fp)))
        return pa.RecordBatch.from_arrays([pa.array(fp[at]), pa.array(fp[top[at]])], names=["a", "b"])

    def run(batches):
        cell, fp = np.zeros(0, np.int64), np.zeros(0, np.int64)
        for b in batches:
            cell = np.concatenate([cell, b.column(0).to_numpy(zero_copy_only=False)])
            fp = np.concatenate([fp, b.column(1).to_numpy(zero_copy_only=False)])
            if len(cell) > rows and cell[0] != cell[-1]:
                cut = int(np.flatnonzero(cell != cell[-1])[-1]) + 1
                yield solve(cell[:cut], fp[:cut])
                cell, fp = cell[cut:], fp[cut:]
        if len(cell):
            yield solve(cell, fp)

    return run


def near_links(fps: DataFrame, radius: int = 2, split: int = 512) -> DataFrame:
    """(a, b): links between distinct fingerprints that connect all that lie within radius (at most 2) bits."""
    if radius > 2:
        raise ValueError("the cells are made for a radius of 2 at most")
    block = [F.shiftrightunsigned("fp", 16 * k).bitwiseAND(F.lit(0xFFFF)) for k in range(4)]
    keyed = F.array(*[F.struct(F.lit(t).alias("t"), F.shiftleft(block[i], 16).bitwiseOR(block[j]).alias("k"), F.shiftleft(block[[x for x in range(4) if x not in (i, j)][0]], 16).bitwiseOR(block[[x for x in range(4) if x not in (i, j)][1]]).alias("rest")) for t, (i, j) in enumerate(PAIRS)])
    rows = fps.select("fp").distinct().select("fp", F.explode(keyed).alias("c")).select("fp", F.col("c.t").alias("t"), F.col("c.k").alias("k"), F.col("c.rest").alias("rest"))
    size = rows.groupBy("t", "k").agg(F.count("*").alias("n")).where("n > 1")
    held = rows.join(size, ["t", "k"])
    small = F.col("n") <= split
    bit8 = [F.shiftright("rest", 8 * k).bitwiseAND(F.lit(0xFF)) for k in range(4)]
    deep = F.array(*[F.struct(F.lit(t + 1).alias("u"), F.shiftleft(bit8[i], 8).bitwiseOR(bit8[j]).alias("v")) for t, (i, j) in enumerate(PAIRS)])
    flat = F.array(F.struct(F.lit(0).alias("u"), F.lit(0).cast("long").alias("v")))
    cells = held.select("fp", "t", "k", F.explode(F.when(small, flat).otherwise(deep)).alias("d"))
    # Cells are named by a 64-bit hash; two cells of one name would only be searched together.
    cells = cells.select(F.xxhash64("t", "k", "d.u", "d.v").alias("cell"), "fp")
    return cells.repartition("cell").sortWithinPartitions("cell", "fp").mapInArrow(_cells(radius), "a long, b long")


def near_groups(docs: DataFrame, width: int = 5, radius: int = 2, seed: int = 42) -> DataFrame:
    """(doc_id, fp, component_id): component_id is the smallest doc_id reachable over links of at most radius bits."""
    marks = settle(fingerprints(docs, width, seed), "fingerprints")
    own = marks.groupBy("fp").agg(F.min("doc_id").alias("least"))
    comp = components(near_links(marks, radius).distinct())
    joined = own.join(comp.withColumnRenamed("id", "fp"), "fp", "left").withColumn("comp", F.coalesce("comp", "fp"))
    head = joined.groupBy("comp").agg(F.min("least").alias("component_id"))
    names = settle(joined.join(head, "comp").select("fp", "component_id"), "names")
    return marks.join(names, "fp").select("doc_id", "fp", "component_id")


# -- groups by similarity -------------------------------------------------------------------------------------------------

BANDS = 8
_ODD = (np.random.default_rng(11).integers(1, 1 << 63, 2 * BANDS, dtype=np.int64).astype(np.uint64) << np.uint64(1)) | np.uint64(1)


def _set_of(raw: bytes, width: int, seed: int) -> np.ndarray:
    return np.unique(np.array(shingle_hashes(raw, width, seed), np.uint64))


def _set_name(u: np.ndarray) -> np.uint64:
    with np.errstate(over="ignore"):
        return mix(mix(u).sum(dtype=np.uint64) + np.uint64(len(u)))


def _signatures(width: int, seed: int):
    def run(batches):
        for b in batches:
            data, offs = text_view(b.column(1))
            raw, n = data.tobytes(), len(offs) - 1
            name, bands, sets, held = np.zeros(n, np.uint64), np.zeros((n, BANDS), np.uint64), [], 0
            marks = np.zeros(n, np.uint64)
            for i in range(n):
                u = _set_of(raw[offs[i] : offs[i + 1]], width, seed)
                name[i] = _set_name(u)
                sets.append(u)  # each shingle once: a repeated phrase does not weigh more
                held += len(u)
                with np.errstate(over="ignore"):
                    least = np.array([(u * k).min() for k in _ODD]) if len(u) else np.zeros(2 * BANDS, np.uint64)
                    bands[i] = mix(least[::2] * np.uint64(31) + least[1::2] + np.arange(BANDS, dtype=np.uint64))
                if len(sets) == 64 or held > 1 << 17 or i == n - 1:
                    marks[i + 1 - len(sets) : i + 1] = majority(sets)
                    sets, held = [], 0
            flat = pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * BANDS), pa.array(bands.ravel().view(np.int64)))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(name.view(np.int64)), pa.array(marks.view(np.int64)), flat], names=["doc_id", "name", "fp", "bands"])

    return run


def _marked_sets(width: int, seed: int, bits_b):
    def run(batches):
        bits = bits_b.value
        for b in batches:
            data, offs = text_view(b.column(0))
            raw, names, sets = data.tobytes(), [], []
            for i in range(len(offs) - 1):
                u = _set_of(raw[offs[i] : offs[i + 1]], width, seed)
                v = int(_set_name(u))
                slot = v >> 40
                if bits[slot >> 3] >> (slot & 7) & 1:
                    names.append(v)
                    sets.append(u.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(np.array(names, np.uint64).view(np.int64)), pa.array(sets, pa.binary())], names=["name", "set"])

    return run


def _similar_cells(radius: int, similarity: float, rows: int = 20_000, most: int = 64 << 20):
    """Whole cells at a time: pairs of the Gray index that are not yet connected are verified, then all others of the cell
    that can be similar."""

    def solve(cell, fp, name, sets):
        n, top = len(fp), np.arange(len(fp))
        parts = [np.frombuffer(x, np.uint64) for x in sets]
        size = np.array([len(x) for x in parts])

        def root(i: int) -> int:
            while top[i] != i:
                top[i] = top[top[i]]
                i = top[i]
            return i

        for a, b in GrayIndex(fp.view(np.uint64), cell).links(radius):
            while (top[top] != top).any():
                top[:] = top[top]
            todo = np.flatnonzero(top[a] != top[b])
            for i, j in zip(a[todo].tolist(), b[todo].tolist(), strict=True):
                ri, rj = root(i), root(j)
                if ri != rj:
                    x, y = parts[i], parts[j]
                    if min(len(x), len(y)) >= similarity * max(len(x), len(y)):
                        both = len(np.intersect1d(x, y, assume_unique=True))
                        if both >= similarity * (len(x) + len(y) - both):
                            top[max(ri, rj)] = min(ri, rj)
        for i, near in _prefix_mates(_open(cell, top), cell, parts, similarity):
            while (top[top] != top).any():
                top[:] = top[top]
            near = near[top[near] != top[i]]
            near = near[np.minimum(size[near], size[i]) >= similarity * np.maximum(size[near], size[i])]
            for k in range(0, len(near), 256):
                part = near[k : k + 256]
                part = part[top[part] != top[i]]
                if not len(part):
                    continue
                flat = np.concatenate([parts[j] for j in part])
                at = np.minimum(np.searchsorted(parts[i], flat), size[i] - 1)
                both = np.add.reduceat(parts[i][at] == flat, np.append(0, np.cumsum(size[part])[:-1]))
                for j in part[both >= similarity * (size[part] + size[i] - both)].tolist():
                    ri, rj = root(i), root(j)
                    top[max(ri, rj)] = min(ri, rj)
                while (top[top] != top).any():
                    top[:] = top[top]
        links = [(name[i], name[r]) for i in range(n) if (r := root(i)) != i]
        cols = list(zip(*links, strict=True)) or [[], []]
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=["a", "b"])

    def run(batches):
        held, size = [], 0
        for b in batches:
            for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if held and row[0] != held[-1][0] and (len(held) > rows or size > most):
                    yield solve(*_columns(held))
                    held, size = [], 0
                held.append(row)
                size += len(row[3])
        if held:
            yield solve(*_columns(held))

    return run


def _open(cell: np.ndarray, top: np.ndarray) -> np.ndarray:
    """Places in cells that are not yet connected."""
    while (top[top] != top).any():
        top[:] = top[top]
    _, first, no = np.unique(cell, return_index=True, return_inverse=True)
    apart = np.zeros(len(first), bool)
    apart[no[top != top[first][no]]] = True
    return np.flatnonzero(apart[no])


def _prefix_mates(at: np.ndarray, cell: np.ndarray, parts: list, similarity: float):
    """(i, places after i) of all pairs of a cell among the places at that can have that similarity: with the shingles of each set ordered from
    the rarest in the cell on, such pairs share one of the first |x| - similarity * |x| + 1."""
    size = np.array([len(parts[i]) for i in at], np.int64)
    if not size.sum():
        return
    own = np.repeat(np.arange(len(at)), size)
    _, token = np.unique(np.concatenate([parts[i] for i in at]), return_inverse=True)
    cells, no = np.unique(cell[at], return_inverse=True)
    _, token, count = np.unique(token * len(cells) + no[own], return_inverse=True, return_counts=True)
    order = np.lexsort((token, count[token], own))
    own, token = own[order], token[order]
    place = np.arange(len(own)) - np.repeat(np.cumsum(size) - size, size)
    first = place < (size - np.ceil(similarity * size - 1e-9) + 1)[own]
    own, token = own[first], token[first]
    post = np.argsort(token, kind="stable")  # the sets of each shingle, in order
    lo = np.searchsorted(token[post], token)
    hi = np.searchsorted(token[post], token, "right")
    shared = hi - lo > 1
    for i in np.unique(own[shared]).tolist():
        a, b = np.searchsorted(own, [i, i + 1])
        mates = np.unique(np.concatenate([own[post[x:y]] for x, y in zip(lo[a:b].tolist(), hi[a:b].tolist(), strict=True)]))
        mates = mates[mates > i]
        if len(mates):
            yield int(at[i]), at[mates]


def _columns(held: list) -> tuple:
    c, f, n, s = zip(*held, strict=True)
    return np.array(c, np.int64), np.array(f, np.int64), n, s


def similar_groups(docs: DataFrame, width: int = 5, similarity: float = 0.8, radius: int = 20, seed: int = 42) -> DataFrame:
    """(doc_id, component_id): texts whose shingle sets have at least that Jaccard similarity are linked.

    At this similarity fingerprints differ in ten bits or so, too many for pigeonhole cells; cells are named by bands of two
    minima of the shingle hashes instead (eight bands lose three pairs of ten thousand at 0.8, fewer above). Equal sets are
    one; sets that share no cell are not fetched; in a cell the Gray index first gives pairs within `radius` bits, whose sets
    are compared exactly unless they are connected already, and then sets that are still apart are compared exactly where
    one of their rarest shingles is the same, which holds for every similar pair. The radius decides only the order.
    """
    spark = docs.sparkSession
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    marks = settle(src.mapInArrow(_signatures(width, seed), "doc_id long, name long, fp long, bands array<long>"), "signatures")
    own = marks.groupBy("name").agg(F.min("doc_id").alias("least"), F.max("fp").alias("fp"), F.first("bands").alias("bands"))
    cells = own.select("name", "fp", F.explode("bands").alias("cell"))
    shared = cells.groupBy("cell").agg(F.count("*").alias("k")).where("k > 1").select("cell")
    held = settle(cells.join(shared, "cell").select("cell", "fp", "name"), "cells")
    # A bitmap of 2^24 bits names the sets to fetch; when it is crowded it only lets more sets through.
    slots = held.select(F.shiftrightunsigned("name", 40).alias("s")).groupBy(F.shiftright("s", 3).alias("byte")).agg(F.expr("bit_or(shiftleft(1, cast(s & 7 as int))) as v")).toArrow()
    bits = np.zeros(1 << 21, np.uint8)
    bits[slots.column("byte").to_numpy()] = slots.column("v").to_numpy()
    sets = src.select("text").mapInArrow(_marked_sets(width, seed, spark.sparkContext.broadcast(bits)), "name long, set binary").groupBy("name").agg(F.max("set").alias("set"))
    full = held.join(sets, "name").select("cell", "fp", "name", "set")
    links = full.repartition("cell").sortWithinPartitions("cell", "name").mapInArrow(_similar_cells(radius, similarity), "a long, b long")
    comp = components(links.distinct())
    least = own.select("name", "least").join(comp.withColumnRenamed("id", "name"), "name", "left").withColumn("comp", F.coalesce("comp", "name"))
    head = least.groupBy("comp").agg(F.min("least").alias("component_id"))
    names = settle(least.join(head, "comp").select("name", "component_id"), "names")
    return marks.select("doc_id", "name").join(names, "name").select("doc_id", "component_id")


def one_of_each(docs: DataFrame) -> DataFrame:
    """docs, all columns: of each group of similar texts the row with the smallest doc_id."""
    keep = similar_groups(docs).where(F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias("kept")).distinct()
    rows = docs.select(F.struct(*docs.columns).alias("r"), F.col("doc_id").cast("long").alias("k"))
    return rows.join(keep, F.col("k").eqNullSafe(F.col("kept")), "left_semi").select("r.*")


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = near_groups(documents(spark, sf_dir, "doc_id", "text"), width=3, radius=2, seed=42)
    return got.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
