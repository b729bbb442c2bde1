"""Line dedup: an exact set-similarity join of lines.

A line is the set of its words; two lines match at a Jaccard similarity of 0.8 or more. A line is removed when an earlier
line matches it; lines are ordered by (doc_id, line number), and earlier lines count whether or not they stay. Words are
ordered by rarity: words that have a share of at least 2^-18 of all words (at most 2^18 of them, whatever the input) have
ranks of their own, the others the rank of their hash bucket, which leaves the frequent words out of its count.
So a line's prefix holds its rarest words, and matching lines share a prefix word.

Equal sets are one (three hash sums of 64 bits: of the words' hashes, of their first bytes, of their parities). A first pass
meets sets by prefix word under length, positional and parity-sketch filters (the sketch is a lower bound of the symmetric
difference, so it loses nothing) and keeps the rows with a candidate. A second pass fetches the words themselves of their
sets, compares them byte by byte and verifies the similarity; a pair counts in the cell of its first common word only.
A word in more than `block` sets, and a cell of more than `volume` words, is dealt out as pairs of blocks. Nothing is
emitted by pair, only by set.

Lines without a word stay and match nothing. Null or empty texts have no such line. Rows that repeat a doc_id get the
decisions of that id; a null doc_id comes before all others. Empty tables give empty results; extra columns, of whatever
name, are carried along untouched. Bytes that are not UTF-8 are words like any other.
"""
from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bytescan import SPACE, mix, prefix_sums, runs, span_hash
from .common import blocks, documents, release, settle, text_view

BUCKETS = 1 << 16  # of words that are not frequent
SHARE = 1 << 18  # a frequent word is at least one in so many
FIRST = -(1 << 63)
STEP = 1 << 17  # bytes whose arrays stay in a core's cache
#: Similarity as a fraction: 4 / 5.
NUM, DEN = 4, 5
_LOW = np.uint64((1 << 32) - 1)
_BITS = np.uint64(19)  # of a key hold the rank
_REST = np.uint64(64) - _BITS


def _lines(data: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """Places where a line starts."""
    start = np.zeros(len(data) + 1, bool)
    start[1:] = data == 10
    start[offs] = True
    return np.flatnonzero(start[: len(data)])


def _line_hashes(data: np.ndarray, at: np.ndarray, sums: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """End of each line, its line feed left out, and the hash of its bytes."""
    end = np.append(at[1:], len(data))[: len(at)]
    if len(end):
        end = end - (data[end - 1] == 10)
    return end, span_hash(sums, at, end)


def _heads(data: np.ndarray, s: np.ndarray, e: np.ndarray) -> np.ndarray:
    """The first eight bytes of each word and its length, mixed: tells apart words whose hashes agree by chance."""
    eight = np.ndarray(len(data) + 1, ">u8", np.concatenate([data, np.zeros(8, np.uint8)]), strides=1)[s].astype(np.uint64)
    size = (e - s).astype(np.uint64)
    behind = np.uint64(64) - np.minimum(size, np.uint64(8)) * np.uint64(8)
    return mix(eight >> behind << behind ^ mix(size))


# -- rarity ---------------------------------------------------------------------------------------------------------------


def _distinct(x: np.ndarray) -> np.ndarray:
    """Sorted distinct values."""
    x = np.sort(x)
    return x[np.append(True, x[1:] != x[:-1])] if len(x) else x


def _coded(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted distinct values, a place of each, and each place's number among them."""
    order = np.argsort(x)
    y = x[order]
    fresh = np.append(True, y[1:] != y[:-1])[: len(y)]
    code = np.empty(len(x), np.int64)
    code[order] = np.cumsum(fresh) - 1
    return y[fresh], order[fresh], code


def _word_counts(batches, most: int = 1 << 21):
    """Of chunks of about `most` words: (k, c), the words of each hash bucket, and (h, c, k null), those that have a share of
    2^-18 of their chunk. A word with this share of all words has it in some chunk."""
    held, size = [], 0

    def out():
        h = np.sort(np.concatenate(held))
        at = np.flatnonzero(np.append(True, h[1:] != h[:-1]))
        n = np.diff(np.append(at, len(h)))
        often = n * SHARE >= len(h)
        total = np.bincount((h >> np.uint64(48)).astype(np.int64), minlength=BUCKETS)
        k = np.flatnonzero(total)
        none = pa.nulls(int(often.sum()), pa.int32())
        yield pa.RecordBatch.from_arrays([none, pa.array(h[at[often]].view(np.int64)), pa.array(n[often])], names=["k", "h", "c"])
        yield pa.RecordBatch.from_arrays([pa.array(k.astype(np.int32)), pa.nulls(len(k), pa.int64()), pa.array(total[k])], names=["k", "h", "c"])

    for b in batches:
        data, offs = text_view(b.column(0))
        for lo, hi in blocks(offs, STEP):
            text = data[offs[lo] : offs[hi]]
            s, e = runs(~SPACE[text], offs[lo : hi + 1] - offs[lo])
            held.append(span_hash(prefix_sums(text), s, e))
            size += len(s)
            if size > most:
                yield from out()
                held, size = [], 0
    if size:
        yield from out()


class Rarity:
    """Keys of words: rank in the upper bits, hash below. Frequent words and buckets of the others are ranked together by count;
    no word below the rank `common` stands in more than `block` sets."""

    def __init__(self, words: np.ndarray, counts: np.ndarray, buckets: np.ndarray, block: int):
        order = np.argsort(words)
        self.words, counts = words[order], counts[order]
        slot = (self.words >> np.uint64(48)).astype(np.int64)
        # Counts of words are lower bounds, those of whole buckets exact, so what they leave bounds every other word.
        left = buckets - np.bincount(slot, weights=counts, minlength=BUCKETS).astype(np.int64)
        every = np.concatenate([left, np.where(buckets[slot] <= block, counts, np.maximum(counts, block + 1))])
        rank = np.empty(len(every), np.uint64)
        rank[np.lexsort((np.arange(len(every)), every))] = np.arange(len(every), dtype=np.uint64)
        self.own, self.bucket = rank[BUCKETS:], rank[:BUCKETS]
        self.common = int((every <= block).sum())

    def keys(self, h: np.ndarray) -> np.ndarray:
        rank = self.bucket[(h >> np.uint64(48)).astype(np.int64)]
        if len(self.words):
            at = np.minimum(np.searchsorted(self.words, h), len(self.words) - 1)
            rank = np.where(self.words[at] == h, self.own[at], rank)
        return rank << _REST | mix(h) >> _BITS


def rarity(docs: DataFrame, block: int) -> Rarity:
    """The tables that reach the driver have at most 2^16 and 2^18 rows, by arithmetic."""
    counts = settle(docs.select(F.col("text").cast("string")).mapInArrow(_word_counts, "k int, h long, c long").groupBy("k", "h").agg(F.sum("c").alias("c")), "words")
    rest = counts.where("k is not null").select("k", "c").toArrow()
    buckets = np.zeros(BUCKETS, np.int64)
    buckets[rest.column("k").to_numpy()] = rest.column("c").to_numpy()
    frequent = counts.where(F.col("k").isNull() & (F.col("c") * SHARE >= int(buckets.sum()))).select("h", "c").toArrow()
    release(counts)
    return Rarity(frequent.column("h").to_numpy().view(np.uint64), frequent.column("c").to_numpy(), buckets, block)


def prefix_size(n: np.ndarray) -> np.ndarray:
    return n - -(-NUM * n // DEN) + 1


# -- sets -----------------------------------------------------------------------------------------------------------------


class Sets:
    """The word sets of the lines of some texts, each set's words from the rarest on, a line's repeats left out."""

    def __init__(self, data: np.ndarray, offs: np.ndarray, rank: Rarity):
        s, e = runs(~SPACE[data], offs)
        sums = prefix_sums(data)
        h = span_hash(sums, s, e)
        at = _lines(data, offs)
        line = np.repeat(np.arange(len(at)), np.diff(np.append(np.searchsorted(s, at), len(s))))
        doc, whole = np.searchsorted(offs, at, "right") - 1, _line_hashes(data, at, sums)[1]
        number = np.arange(len(at)) - np.searchsorted(doc, np.arange(len(offs) - 1))[doc] if len(at) else at
        u, at, code = _coded(h)
        self.from_, self.to = s[at], e[at]
        key = rank.keys(u)
        order = np.argsort(key)
        self.from_, self.to, key = self.from_[order], self.to[order], key[order]
        place = np.empty(len(u), np.int64)
        place[order] = np.arange(len(u))
        both = _distinct(line.astype(np.uint64) << np.uint64(32) | place[code].astype(np.uint64))
        line, self.code = (both >> np.uint64(32)).astype(np.int64), (both & _LOW).astype(np.int64)
        self.key = key[self.code]
        self.start = np.flatnonzero(np.append(True, line[1:] != line[:-1])) if len(line) else np.zeros(0, np.int64)
        self.n = np.diff(np.append(self.start, len(line)))
        own = line[self.start]
        self.doc, self.line, self.whole = doc[own], number[own], whole[own]
        with np.errstate(over="ignore"):
            self.sid = self._sums(mix(key)) + self.n.astype(np.uint64)
            self.sid2 = self._sums(_heads(data, self.from_, self.to) + key)
        bits = mix(key ^ np.uint64(0x5DEECE66D))
        self.bit, self.upper = np.uint64(1) << (bits & np.uint64(63)), bits >> np.uint64(6) & np.uint64(1)

    def _sums(self, of: np.ndarray) -> np.ndarray:
        return np.add.reduceat(of[self.code], self.start) if len(self.start) else np.zeros(0, np.uint64)

    def sketch(self) -> tuple[np.ndarray, np.ndarray]:
        """Parity of the words' hash bits, 128 of them: each word that two sets do not share changes one bit at most."""
        low, high = self.bit * (np.uint64(1) - self.upper), self.bit * self.upper
        if not len(self.start):
            return low, high
        return np.bitwise_xor.reduceat(low[self.code], self.start), np.bitwise_xor.reduceat(high[self.code], self.start)

    def texts(self, data: np.ndarray, at: np.ndarray) -> pa.Array:
        """The words of the sets `at`, rarest first, each with a space behind it."""
        edge = np.concatenate([[0], np.cumsum(self.n[at])])
        code = self.code[np.repeat(self.start[at] - edge[:-1], self.n[at]) + np.arange(edge[-1])]
        size = self.to[code] - self.from_[code] + 1
        stop = np.cumsum(size)
        flat = data[np.minimum(np.repeat(self.from_[code] - (stop - size), size) + np.arange(int(stop[-1]) if len(stop) else 0), max(0, len(data) - 1))]
        flat[stop - 1] = 32
        bounds = np.concatenate([[0], stop])[edge].astype(np.int64)
        return pa.Array.from_buffers(pa.large_binary(), len(at), [None, pa.py_buffer(bounds), pa.py_buffer(flat)]).cast(pa.binary())


def _line_rows(rank_b):
    def run(batches):
        rank = rank_b.value
        for b in batches:
            data, offs = text_view(b.column(1))
            ids = b.column(0).to_numpy(zero_copy_only=False)
            for lo, hi in blocks(offs, STEP):
                s = Sets(data[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo], rank)
                pre = prefix_size(s.n)
                edge = np.concatenate([[0], np.cumsum(pre)])
                flat = s.key[np.repeat(s.start - edge[:-1], pre) + np.arange(edge[-1])]
                low, high = s.sketch()
                prefix = pa.ListArray.from_arrays(pa.array(edge.astype(np.int32)), pa.array(flat.view(np.int64)))
                yield pa.RecordBatch.from_arrays([pa.array(s.sid.view(np.int64)), pa.array(s.sid2.view(np.int64)), pa.array(ids[lo + s.doc]), pa.array(s.line.astype(np.int32)), pa.array(s.whole.view(np.int64)), pa.array(s.n.astype(np.int32)), pa.array(low.view(np.int64)), pa.array(high.view(np.int64)), prefix], names=["sid", "sid2", "doc_id", "line", "whole", "n", "sketch", "sketch2", "prefix"])

    return run


def _set_texts(rank_b, bits_b):
    """Words of the sets of the lines whose bit is set."""

    def run(batches):
        rank, bits = rank_b.value, bits_b.value
        for b in batches:
            data, offs = text_view(b.column(0))
            for lo, hi in blocks(offs, STEP):
                part = data[offs[lo] : offs[hi]]
                at = _lines(part, offs[lo : hi + 1] - offs[lo])
                end, whole = _line_hashes(part, at, prefix_sums(part))
                slot = (whole >> np.uint64(40)).astype(np.int64)
                mine = np.flatnonzero((bits[slot >> 3] >> (slot & 7)) & 1)
                mine = mine[np.unique(whole[mine], return_index=True)[1]]
                size = end[mine] - at[mine]
                stop = np.cumsum(size)
                text = part[np.repeat(at[mine] - (stop - size), size) + np.arange(int(stop[-1]) if len(stop) else 0)]
                s = Sets(text, np.concatenate([[0], stop]), rank)
                yield pa.RecordBatch.from_arrays([pa.array(s.sid.view(np.int64)), pa.array(s.sid2.view(np.int64)), s.texts(text, np.arange(len(s.n)))], names=["sid", "sid2", "words"])

    return run


# -- cells ----------------------------------------------------------------------------------------------------------------


def _windows(cell: np.ndarray, side: np.ndarray, n: np.ndarray, limit: int = 1 << 18):
    """Pairs (i, j) of rows sorted by (cell, n) that share a cell and may match by length; side -1 meets all, sides 0 and 1 meet
    each other."""
    code = np.cumsum(np.append(0, cell[1:] != cell[:-1])) * (1 << 32)
    stop = np.searchsorted(code + n, code + n * DEN // NUM, "right")
    count = stop - np.arange(len(n)) - 1
    total = np.concatenate([[0], np.cumsum(count)])
    lo = 0
    while lo < len(n):
        hi = max(lo + 1, int(np.searchsorted(total, total[lo] + limit, "right")) - 1)
        c = count[lo:hi]
        i = np.repeat(np.arange(lo, hi), c)
        j = i + 1 + np.arange(len(i)) - np.repeat(total[lo:hi] - total[lo], c)
        ok = (side[i] < 0) | (side[i] != side[j])
        yield i[ok], j[ok]
        lo = hi


def _unpack(packed: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Size, position and side of a posting."""
    return packed >> 32, packed >> 2 & 0x3FFFFFFF, (packed & 3) - 1


def _filtered(cell, side, n, pos, lead, low, high):
    """Pairs that may match and may have their first common word in this cell: not those behind an equal first word."""
    for i, j in _windows(cell, side, n):
        both = n[i] + n[j]
        need = -(-NUM * both // (NUM + DEN))
        most = np.minimum(pos[i], pos[j]) + np.minimum(n[i] - pos[i], n[j] - pos[j])
        ok = (most >= need) & (np.bitwise_count(low[i] ^ low[j]).astype(np.int64) + np.bitwise_count(high[i] ^ high[j]) <= both - 2 * need)
        ok &= (pos[i] == 0) | (pos[j] == 0) | (lead[i] != lead[j])
        if ok.any():
            yield i[ok], j[ok]


def _whole_cells(batches, solve, most: int = 1 << 16, volume: int = 2 << 20):
    """Feeds solve with rows sorted by cell, whole cells at a time, of about `most` rows or `volume` bytes."""
    held, rows, size = [], 0, 0
    for b in batches:
        held.append(b)
        rows, size = rows + b.num_rows, size + b.nbytes
        if rows > most or size > most * 64 + volume:
            t = pa.Table.from_batches(held).combine_chunks()
            cell = t.column(0).to_numpy()
            edge = np.flatnonzero(cell[1:] != cell[:-1]) + 1
            lo = 0
            per = max(1, int(len(cell) * (most * 64 + volume) / max(1, size)))
            while len(edge) and lo < edge[-1]:
                hi = int(edge[min(len(edge) - 1, np.searchsorted(edge, lo + min(most, per)))])
                yield from solve(t.slice(lo, hi - lo).combine_chunks())
                lo = hi
            t = t.slice(lo).combine_chunks()
            held, rows, size = t.to_batches(), t.num_rows, int(size * t.num_rows / max(1, len(cell)))
    if rows:
        yield from solve(pa.Table.from_batches(held).combine_chunks())


def _arrays(t: pa.Table, n: int) -> list[np.ndarray]:
    return [t.column(i).to_numpy() for i in range(n)]


_POST = "cell long, packed long, sketch long, sketch2 long, lead long, id long"


def _mark(batches):
    def solve(t):
        cols = _arrays(t, 6)
        order = np.lexsort((cols[1], cols[0]))
        cell, packed, low, high, lead, _ = cols = [v[order] for v in cols]
        n, pos, side = _unpack(packed)
        hit = np.zeros(len(n), bool)
        for i, j in _filtered(cell, side, n, pos, lead, low.view(np.uint64), high.view(np.uint64)):
            hit[i] = hit[j] = True
        yield pa.RecordBatch.from_arrays([pa.array(v[hit]) for v in cols], names=[x.split()[0] for x in _POST.split(", ")])

    yield from _whole_cells(batches, solve)


class Words:
    """The words of some sets as numbers, sets end to end; words with one number are equal byte by byte."""

    def __init__(self, texts: pa.Array):
        data, offs = text_view(texts)
        s, e = runs(data != 32, offs)
        h = np.empty(len(s), np.uint64)
        for lo, hi in blocks(offs, STEP):
            a, b = np.searchsorted(s, offs[[lo, hi]])
            h[a:b] = span_hash(prefix_sums(data[offs[lo] : offs[hi]]), s[a:b] - offs[lo], e[a:b] - offs[lo])
        self.base = np.searchsorted(s, offs[:-1])
        self.size = np.diff(np.append(self.base, len(s)))
        names, first, code = _coded(h)
        if not self._same(data, s, e, first[code]):
            raw = data.tobytes()
            known: dict[bytes, int] = {}
            code = np.array([known.setdefault(raw[a:b], len(known)) for a, b in zip(s.tolist(), e.tolist(), strict=True)])
            names = np.arange(len(known))
        self.code, self.k = code, max(1, len(names))
        self.table = np.sort(np.repeat(np.arange(len(self.size)), self.size) * self.k + code)

    @staticmethod
    def _same(data, s, e, rep, step: int = 1 << 16) -> bool:
        size = e - s
        if (size != size[rep]).any():
            return False
        for lo in range(0, len(s), step):
            c = size[lo : lo + step]
            stop = np.cumsum(c)
            run = np.arange(int(stop[-1])) - np.repeat(stop - c, c)
            if (data[np.repeat(s[lo : lo + step], c) + run] != data[np.repeat(s[rep[lo : lo + step]], c) + run]).any():
                return False
        return True

    def has(self, own: np.ndarray, code: np.ndarray) -> np.ndarray:
        """Whether set own[i] holds the word code[i]."""
        want = own * self.k + code
        return self.table[np.minimum(np.searchsorted(self.table, want), len(self.table) - 1)] == want


def _matches(w: Words, own, pos, n, i, j, limit: int = 1 << 19):
    """The pairs whose first common word is that of their cell and whose similarity is high enough."""
    a, b = own[i], own[j]
    same = w.code[w.base[a] + pos[i]] == w.code[w.base[b] + pos[j]]
    i, j, a, b = i[same], j[same], a[same], b[same]
    live, todo, r = np.ones(len(i), bool), np.flatnonzero((pos[i] > 0) & (pos[j] > 0)), 0
    while len(todo):
        hit = w.has(a[todo], w.code[w.base[b[todo]] + r])
        live[todo[hit]] = False
        r += 1
        todo = todo[~hit]
        todo = todo[pos[j[todo]] > r]
    i, j, a, b = i[live], j[live], a[live], b[live]
    c = n[j] - pos[j]
    stop = np.cumsum(c)
    lo = 0
    while lo < len(i):
        hi = max(lo + 1, int(np.searchsorted(stop, (stop[lo - 1] if lo else 0) + limit, "right")))
        c_, at = c[lo:hi], np.cumsum(c[lo:hi])
        step = np.arange(int(at[-1])) - np.repeat(at - c_, c_)
        both = np.add.reduceat(w.has(np.repeat(a[lo:hi], c_), w.code[np.repeat(w.base[b[lo:hi]] + pos[j[lo:hi]], c_) + step]).astype(np.int64), at - c_)
        ok = DEN * both >= NUM * (n[i[lo:hi]] + n[j[lo:hi]] - both)
        yield i[lo:hi][ok], j[lo:hi][ok]
        lo = hi


def _verify(batches):
    def solve(t):
        cols = _arrays(t, 8)
        order = np.lexsort((cols[1], cols[0]))
        cell, packed, low, high, lead, sid, doc, line = (v[order] for v in cols)
        n, pos, side = _unpack(packed)
        _, first, own = np.unique(sid, return_index=True, return_inverse=True)
        words = Words(t.column(8).combine_chunks().take(pa.array(order[first])))
        links, late = np.zeros(len(n), np.int64), np.zeros(len(n), bool)
        for i, j in _filtered(cell, side, n, pos, lead, low.view(np.uint64), high.view(np.uint64)):
            for a, b in _matches(words, own, pos, n, i, j):
                links += np.bincount(a, minlength=len(n)) + np.bincount(b, minlength=len(n))
                after = (doc[a] > doc[b]) | (doc[a] == doc[b]) & (line[a] > line[b])
                late[np.where(after, a, b)] = True
        at = np.flatnonzero(links)
        yield pa.RecordBatch.from_arrays([pa.array(sid[at]), pa.array(links[at]), pa.array(late[at])], names=["id", "links", "late"])

    yield from _whole_cells(batches, solve)


_COLS = ["packed", "sketch", "sketch2", "lead", "id"]


def _packed(side):
    return F.shiftleft(F.shiftright("packed", 2), 2).bitwiseOR(side.cast("long") + 1).alias("packed")


def _dealt(rows: DataFrame, parts) -> DataFrame:
    """Rows of cells that are dealt to pairs of `parts` blocks; sides keep apart what they kept apart."""
    side, mine = (F.col("packed").bitwiseAND(3) - 1).cast("int"), F.pmod(F.xxhash64("id"), F.col("parts")).cast("int")
    every = F.sequence(F.lit(0), F.col("parts") - 1)
    grid = F.transform(every, lambda o: F.struct(F.least(o, F.col("mine")).alias("i"), F.greatest(o, F.col("mine")).alias("j"), F.when(o == F.col("mine"), F.lit(-1)).otherwise((F.col("mine") > o).cast("int")).alias("side")))
    across = F.transform(every, lambda o: F.struct(F.when(F.col("side") == 0, F.col("mine")).otherwise(o).alias("i"), F.when(F.col("side") == 0, o).otherwise(F.col("mine")).alias("j"), F.col("side").alias("side")))
    out = rows.withColumn("parts", parts).withColumn("mine", mine).withColumn("side", side).withColumn("g", F.explode(F.when(F.col("side") < 0, grid).otherwise(across)))
    return out.select(F.xxhash64("cell", "g.i", "g.j").alias("cell"), _packed(F.col("g.side")), *_COLS[1:])


def _postings(sets: DataFrame) -> DataFrame:
    """A row (cell, packed, sketch, sketch2, lead, id) for each word of a prefix."""
    post = sets.select("id", F.col("n").alias("size"), "sketch", "sketch2", F.col("prefix")[0].alias("lead"), F.posexplode("prefix").alias("pos", "cell"))
    return post.select("cell", (F.shiftleft(F.col("size").cast("long"), 32) + F.shiftleft(F.col("pos").cast("long"), 2)).alias("packed"), "sketch", "sketch2", F.when(F.col("pos") > 0, F.col("lead")).otherwise(0).alias("lead"), "id")


def _celled(sets: DataFrame, block: int, common: int) -> DataFrame:
    """Postings dealt to cells: a word's rows together, or by pairs of blocks where a word of a common rank stands in more than
    `block` sets."""
    rows = _postings(sets)
    rank = F.shiftrightunsigned("cell", int(_REST))
    # Prefixes stand in order of rank: few end in a common one.
    often = _postings(sets.where(F.shiftrightunsigned(F.element_at("prefix", -1), int(_REST)) >= common)).where(rank >= common)
    count = often.groupBy("cell").agg(F.count("*").alias("k")).where("k > 1")
    held = often.join(count, "cell")
    small = held.where(F.col("k") <= block).select("cell", *_COLS)
    large = _dealt(held.where(F.col("k") > block), F.ceil(F.col("k") / block).cast("int"))
    return rows.where(rank < common).unionByName(small).unionByName(large).repartition("cell").sortWithinPartitions("cell")


def line_decisions(docs: DataFrame, block: int = 4096, volume: int = 1 << 20) -> DataFrame:
    """(doc_id, n_lines, n_removed, removed, n_links) for each document that has a line with a word: removed holds line numbers
    from 0, n_links the matches of its lines' sets with other sets."""
    spark = docs.sparkSession
    src = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(FIRST)).alias("doc_id"), F.col("text").cast("string").alias("text"))
    ranks = rarity(src, block)
    rank = spark.sparkContext.broadcast(ranks)
    kind = "sid long, sid2 long, doc_id long, line int, whole long, n int, sketch long, sketch2 long, prefix array<long>"
    wide = settle(src.mapInArrow(_line_rows(rank), kind), "lines")
    same, sizes = ["sid", "sid2"], ["n", "sketch", "sketch2"]
    merged = wide.groupBy(*same).agg(*[F.max(c).alias(c) for c in sizes], F.min(F.struct("doc_id", "line", "whole")).alias("first"), F.first("prefix").alias("prefix"), F.count("*").alias("c"))
    sets = settle(merged.select(*same, *sizes, F.col("first.doc_id").alias("first"), F.col("first.line").alias("at"), "first.whole", "prefix", "c", F.monotonically_increasing_id().alias("id")), "sets")
    lines = settle(wide.select(*same, "doc_id", "line"), "places")  # all that is asked of the lines from here on
    release(wide)
    marked = settle(_celled(sets, block, ranks.common).mapInArrow(_mark, _POST), "marked")
    names = settle(marked.select("id").distinct().join(sets.select("id", *same, "first", "at", "whole", "c"), "id"), "names")
    # A bitmap of 2^24 bits names the lines of marked sets to the scan; when it is crowded it only lets more lines through.
    slots = names.select(F.shiftrightunsigned("whole", 40).alias("s")).groupBy(F.shiftright("s", 3).alias("byte")).agg(F.expr("bit_or(shiftleft(1, cast(s & 7 as int))) as v")).toArrow()
    bits = np.zeros(1 << 21, np.uint8)
    bits[slots.column("byte").to_numpy()] = slots.column("v").to_numpy()
    words = src.select("text").mapInArrow(_set_texts(rank, spark.sparkContext.broadcast(bits)), "sid long, sid2 long, words binary").groupBy("sid", "sid2").agg(F.max("words").alias("words"))
    where = names.join(words, ["sid", "sid2"]).select("id", "first", "at", "words")
    # Cells of very many words are dealt once more, so that a task never holds more than two such blocks.
    heavy = marked.groupBy("cell").agg(F.sum(F.shiftright("packed", 32)).alias("size")).where(F.col("size") > volume)
    at = marked.join(heavy, "cell", "left")
    dealt = at.where("size is null").select("cell", *_COLS).unionByName(_dealt(at.where("size is not null"), F.ceil(F.col("size") / volume).cast("int")))
    full = dealt.join(where, "id").select("cell", *_COLS, "first", "at", "words")
    seen = full.repartition("cell").sortWithinPartitions("cell").mapInArrow(_verify, "id long, links long, late boolean")
    found = settle(seen.groupBy("id").agg(F.sum("links").alias("links"), F.max("late").alias("late")), "found")
    # Only marked sets have links; of the others those of one line tell nothing.
    linked, alone = names.join(found, "id", "left"), sets.where("c > 1").join(names.select("id"), "id", "left_anti")
    info = linked.where("c > 1 or links is not null").select(*same, "first", "at", "c", "links", "late").unionByName(alone.select(*same, "first", "at", "c", F.lit(None).cast("long").alias("links"), F.lit(None).cast("boolean").alias("late")))
    # Sets that hold more than a 4096th of all lines are fewer than 4096: they meet their lines by broadcast.
    total = lines.count()
    hot = F.broadcast(info.where(F.col("c") > total // 4096).drop("c"))
    cold = info.where(F.col("c") <= total // 4096).drop("c")
    judged = lines.join(hot, same).unionByName(lines.join(hot.select(*same), same, "left_anti").join(cold, same, "left"))
    gone = F.coalesce(F.col("late"), F.lit(False)) | (F.col("first").isNotNull() & ((F.col("doc_id") != F.col("first")) | (F.col("line") != F.col("at"))))
    by = judged.groupBy("doc_id").agg(F.count("*").alias("n_lines"), F.sum(gone.cast("long")).alias("n_removed"), F.array_distinct(F.sort_array(F.collect_list(F.when(gone, F.col("line"))))).alias("removed"), F.coalesce(F.sum("links"), F.lit(0)).alias("n_links"))
    out = settle(by, "decisions")
    for t in (lines, sets, marked, names, found):
        release(t)
    return out


def without_repeats(docs: DataFrame) -> DataFrame:
    """docs, all columns, with the lines removed from text (n_chars follows where there is such a column)."""
    cut = line_decisions(docs).where("n_removed > 0").select(F.col("doc_id").alias("k"), F.col("removed").alias("gone"))
    rows = docs.select(F.struct(*docs.columns).alias("r"), F.coalesce(F.col("doc_id").cast("long"), F.lit(FIRST)).alias("k")).join(cut, "k", "left")
    kept = F.array_join(F.filter(F.split("r.text", "\n"), lambda x, i: ~F.array_contains(F.col("gone"), i)), "\n")
    rows = rows.withColumn("t", F.when(F.col("gone").isNull(), F.col("r.text")).otherwise(kept))
    new = {"text": F.col("t").cast(docs.schema["text"].dataType)}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(F.col("gone").isNull(), F.col("r.n_chars")).otherwise(F.char_length("t").cast(docs.schema["n_chars"].dataType))
    return rows.select(*(new.get(c, F.col("r")[c]).alias(c) for c in docs.columns))


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir, "doc_id", "text")
    by = line_decisions(docs)
    return docs.select("doc_id").join(by, F.coalesce(docs["doc_id"].cast("long"), F.lit(FIRST)) == by["doc_id"], "left").select(docs["doc_id"], F.coalesce("n_lines", F.lit(0)).alias("n_lines"), F.coalesce("n_removed", F.lit(0)).alias("n_removed"), F.coalesce("removed", F.array().cast("array<int>")).alias("removed_lines"), F.coalesce("n_links", F.lit(0)).alias("n_links"))
