"""Best-fit packing by a grouping genetic algorithm.

Documents become token ids and an end mark; only those longer than a sequence are cut, with the remainder first. Pieces are
dealt out to islands of a few thousand. On an island a population of packings evolves: crossover injects whole well-filled
bins of one parent into another, removes the bins that then hold a document twice, and puts the displaced documents back
by best fit. Between rounds, bins that are full stay as they are, the documents of the others move to new islands, and
elite bin patterns (lengths of full bins) migrate with them and are injected where documents of those lengths exist.

Null text: empty, one piece that holds the end mark. Repeated rows are packed as often as they stand. An empty table gives
no piece. Extra columns are ignored. Island size bounds a task's memory; the number of islands follows the input.
"""
from __future__ import annotations

import os
import unicodedata
import zlib
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bytescan import prefix_sums, span_hash
from .common import blocks, documents, settle, text_view

SEQUENCE, END = 1024, 2
ISLAND = 4096
PLAIN = 0x3000  # code points below are split here, others by the library itself
HELD = 2_000_000  # words that a worker remembers


def _classes() -> np.ndarray:
    """0 other, 1 letter, 2 number, 3 white space, 9 not assigned."""
    out = np.zeros(PLAIN, np.uint8)
    space = {0x20, 0x85, 0xA0, 0x1680, 0x2028, 0x2029, 0x202F, 0x205F, *range(9, 14), *range(0x2000, 0x200B)}
    for c in range(PLAIN):
        kind = unicodedata.category(chr(c))
        out[c] = 3 if c in space else 1 if kind[0] == "L" else 2 if kind[0] == "N" else 9 if kind == "Cn" or kind == "Mn" and c > 0x36F else 0
    return out


class Encoder:
    """Token ids of many texts: words are cut out with array operations and each distinct word is encoded by the library once."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.lib = Tokenizer.from_file(path)
        self.special = [t.content for t in self.lib.get_added_tokens_decoder().values()]
        self.kind = _classes()
        self.forget()

    def forget(self) -> None:
        self.keys, self.start, self.count = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.ids, self.used = np.zeros(1 << 20, np.uint32), 0

    def _cuts(self, x: np.ndarray, offs: np.ndarray) -> np.ndarray:
        """Starts of words in code points x of texts that end at offs."""
        n = len(x)
        k = self.kind[x]
        first = np.zeros(n + 1, bool)
        first[offs] = True
        run = first[:n].copy()
        run[1:] |= k[1:] != k[:-1]
        space = k == 3
        blank = x == 32
        ends = np.append(run[1:] | first[1:n], True)  # a run ends here
        text_end = first[1 : n + 1]
        start = run & ~space
        joined = np.zeros(n, bool)
        joined[1:] = blank[:-1] & ~first[1:n]
        start &= ~joined
        last = space & ends & ~text_end  # the last blank of a run that a word follows
        start |= last
        start |= run & space
        # The ending 's, 't, 're, 've, 'm, 'll, 'd is a word of its own after a lone apostrophe.
        lone = np.flatnonzero((x == 39) & run & ends & ~joined & ~text_end)
        if len(lone):
            pad = np.append(x, [0, 0, 0])
            one, two = pad[lone + 1], pad[lone + 2]
            within = ~np.append(text_end, [True] * 3)[lone + 1]
            long = within & (((one == 114) | (one == 118)) & (two == 101) | (one == 108) & (two == 108))
            short = np.isin(one, [115, 116, 109, 100])
            size = np.where(short, 1, np.where(long, 2, 0))
            hit = size > 0
            tail = lone[hit] + 1
            start[tail] = False
            rest = tail + size[hit]
            rest = rest[(rest < n)]
            start[rest] = True
        return np.flatnonzero(start)

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of each text, without an end mark."""
        out: list[np.ndarray | None] = [None] * len(texts)
        codes = [np.frombuffer(t.encode("utf-32-le", "surrogatepass"), np.uint32) for t in texts]
        plain = []
        for i, (t, c) in enumerate(zip(texts, codes, strict=True)):
            if not len(c):
                out[i] = np.zeros(0, np.uint32)
            elif c.max() >= PLAIN or (not t.isascii() and (self.kind[c] == 9).any()) or any(s in t for s in self.special):
                out[i] = np.array(self.lib.encode(t, add_special_tokens=False).ids, np.uint32)
            else:
                plain.append(i)
        if not plain:
            return out
        x = np.concatenate([codes[i] for i in plain])
        offs = np.concatenate([[0], np.cumsum([len(codes[i]) for i in plain])])
        s = self._cuts(x, offs)
        e = np.append(s[1:], len(x))
        h, at, back = np.unique(span_hash(prefix_sums(x), s, e), return_index=True, return_inverse=True)
        if len(self.keys) > HELD:
            self.forget()
        place = np.searchsorted(self.keys, h)
        known = np.zeros(len(h), bool)
        if len(self.keys):
            known = self.keys[np.minimum(place, len(self.keys) - 1)] == h
        new = np.flatnonzero(~known)
        if len(new):
            a, b = s[at[new]], e[at[new]]
            raw = x.tobytes()
            words = [str(raw[4 * i : 4 * j], "utf-32-le", "surrogatepass") for i, j in zip(a.tolist(), b.tolist(), strict=True)]
            got = [w.ids for w in self.lib.encode_batch_fast(words, add_special_tokens=False)]
            size = np.fromiter(map(len, got), np.int64, len(got))
            flat = np.fromiter(chain.from_iterable(got), np.uint32, int(size.sum()))
            while self.used + len(flat) > len(self.ids):
                self.ids = np.concatenate([self.ids, np.zeros(len(self.ids), np.uint32)])
            self.ids[self.used : self.used + len(flat)] = flat
            self.start = np.insert(self.start, place[new], self.used + np.cumsum(size) - size)
            self.count = np.insert(self.count, place[new], size)
            self.keys = np.insert(self.keys, place[new], h[new])
            self.used += len(flat)
            place = np.searchsorted(self.keys, h)
        w = place[back]
        size = self.count[w]
        stop = np.cumsum(size)
        ids = self.ids[np.repeat(self.start[w] - (stop - size), size) + np.arange(int(stop[-1]))]
        edge = np.append(0, stop)[np.searchsorted(s, offs)]
        for j, i in enumerate(plain):
            out[i] = ids[edge[j] : edge[j + 1]]
        return out


_ENCODERS: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    if path not in _ENCODERS:
        _ENCODERS[path] = Encoder(path)
    return _ENCODERS[path]


_PIECES = "doc_id long, piece int, start long, length int, ids_crc32 long"


def _cutter(path: str, limit: int, end: int):
    def run(batches):
        enc = encoder(path)
        for b in batches:
            data, offs = text_view(b.column(1))
            ids = b.column(0).to_pylist()
            raw = data.tobytes()
            for lo, hi in blocks(offs):
                rows: list[list] = [[], [], [], [], []]
                got = enc.encode([raw[offs[i] : offs[i + 1]].decode() for i in range(lo, hi)])
                for i, t in enumerate(got):
                    t = np.append(t, np.uint32(end)).astype("<u4")
                    view, n, at, k = memoryview(t.tobytes()), len(t), 0, 0
                    size = n % limit or limit
                    while at < n:
                        for col, v in zip(rows, (ids[lo + i], k, at, size, zlib.crc32(view[4 * at : 4 * (at + size)])), strict=True):
                            col.append(v)
                        at, k, size = at + size, k + 1, limit
                yield pa.RecordBatch.from_arrays([pa.array(rows[0], pa.int64()), pa.array(rows[1], pa.int32()), pa.array(rows[2], pa.int64()), pa.array(rows[3], pa.int32()), pa.array(rows[4], pa.int64())], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return run


def pieces(docs: DataFrame, path: str, limit: int = SEQUENCE, end: int = END) -> DataFrame:
    """One row for each piece of each document."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_cutter(path, limit, end), _PIECES)


# -- one island ---------------------------------------------------------------------------------------------------------


def best_fit(bins: list[list[int]], items: list[int], size: list[int], limit: int) -> list[list[int]]:
    """Put items, longest first, where least room is left; bins is extended in place."""
    room: dict[int, list[int]] = {}
    mask = 0
    for b, held in enumerate(bins):
        r = limit - sum(size[i] for i in held)
        if r:
            room.setdefault(r, []).append(b)
            mask |= 1 << r
    for i in sorted(items, key=size.__getitem__, reverse=True):
        n = size[i]
        fits = mask >> n
        if fits:
            r = n + (fits & -fits).bit_length() - 1
            stack = room[r]
            b = stack.pop()
            if not stack:
                mask &= ~(1 << r)
            bins[b].append(i)
        else:
            r, b = limit, len(bins)
            bins.append([i])
        r -= n
        if r:
            stack = room.setdefault(r, [])
            stack.append(b)
            mask |= 1 << r
    return bins


def least_bins(size: np.ndarray, limit: int) -> int:
    """A lower bound: for each threshold, long items need bins of their own and the room beside them is counted."""
    best = -(-int(size.sum()) // limit)
    half = size > limit // 2
    for a in np.unique(size[~half])[::8].tolist():
        big, mid, low = size > limit - a, half & (size <= limit - a), ~half & (size >= a)
        best = max(best, int(big.sum() + mid.sum()) + max(0, -(-int(size[low].sum() - (mid.sum() * limit - size[mid].sum())) // limit)))
    return best


def evolve(size: list[int], limit: int, seed: int, patterns: list[list[int]] = (), people: int = 6, rounds: int | None = None) -> list[list[int]]:
    """The best packing found for one island."""
    r = np.random.default_rng(seed)
    rounds = rounds or max(30, 60_000 // max(1, len(size)))  # small islands are cheap and get more
    n, goal = len(size), least_bins(np.array(size, np.int64), limit) if size else 0
    everyone = list(range(n))

    def fitness(bins):
        return len(bins), -sum((sum(size[i] for i in b) / limit) ** 2 for b in bins)

    first = best_fit([], everyone, size, limit)
    crowd = [(fitness(first), first)]
    if len(first) <= goal:
        return first
    if patterns:  # elite patterns of other islands, where their lengths exist here
        stock: dict[int, list[int]] = {}
        for i in everyone:
            stock.setdefault(size[i], []).append(i)
        bins, used = [], set()
        for p in patterns:
            need = {v: p.count(v) for v in set(p)}
            if all(len(stock.get(v, ())) >= c for v, c in need.items()):
                held = [stock[v].pop() for v in p]
                bins.append(held)
                used.update(held)
        bins = best_fit(bins, [i for i in everyone if i not in used], size, limit)
        crowd.append((fitness(bins), bins))
    while len(crowd) < people:  # best fit after random whole bins of chance order
        part = r.permutation(n)[: n // 3].tolist()
        seedbins, held, full = [], [], 0
        for i in part:
            if full + size[i] <= limit:
                held.append(i)
                full += size[i]
            else:
                if full >= limit - 4:
                    seedbins.append(held)
                held, full = [i], size[i]
        used = {i for b in seedbins for i in b}
        bins = best_fit(seedbins, [i for i in everyone if i not in used], size, limit)
        crowd.append((fitness(bins), bins))
    crowd.sort(key=lambda c: c[0])
    idle = 0
    for _ in range(rounds):
        if crowd[0][0][0] <= goal or idle >= max(10, rounds // 3):
            break
        a, b = crowd[int(r.integers(0, max(1, people // 2)))][1], crowd[int(r.integers(0, people))][1]
        full = [x for x in b if sum(size[i] for i in x) >= limit - 1]
        pick = [full[i] for i in r.permutation(len(full))[: max(1, len(full) // 3)].tolist()] if full else []
        inside = {i for x in pick for i in x}
        kept, loose = [], []
        for x in a:
            if inside.isdisjoint(x):
                kept.append(x)
            else:
                loose += [i for i in x if i not in inside]
        # Mutation: the least filled bins, and a few by chance, are dissolved too.
        kept.sort(key=lambda x: sum(size[i] for i in x), reverse=True)
        for x in kept[-max(1, len(kept) // 50) :]:
            loose += x
        kept = [list(x) for x in kept[: -max(1, len(kept) // 50)]]
        child = best_fit(kept + [list(x) for x in pick], loose, size, limit)
        score = fitness(child)
        idle = 0 if score < crowd[0][0] else idle + 1
        if all(score != c[0] for c in crowd):
            crowd.append((score, child))
            crowd.sort(key=lambda c: c[0])
            del crowd[people:]
    return crowd[0][1]


_PACKED = "doc_id long, piece int, start long, length int, ids_crc32 long, sequence_id long, offset long, filled int, lead boolean, lengths array<int>"


def _island(limit: int, turn: int):
    def run(table: pa.Table) -> pa.Table:
        marks = table.column("mark").to_pylist()
        rows = [i for i, m in enumerate(marks) if m == 0]
        patterns = [p for p, m in zip(table.column("lengths").to_pylist(), marks, strict=True) if m == 1]
        own = table.take(pa.array(rows, pa.int64()))
        if not rows:
            return _none()
        own = own.sort_by([("length", "descending"), ("doc_id", "ascending"), ("piece", "ascending")])
        size = own.column("length").to_pylist()
        island = own.column("island")[0].as_py()
        bins = evolve(size, limit, seed=island * 31 + turn, patterns=sorted(patterns)[:512])
        seq, off, fill, lead, shape = ([None] * len(size) for _ in range(5))
        for k, b in enumerate(bins):
            at = 0
            for j, i in enumerate(b):
                seq[i], off[i], lead[i] = turn << 60 | island << 24 | k, at, j == 0
                at += size[i]
            for i in b:
                fill[i] = at
            shape[b[0]] = [size[i] for i in b] if at == limit and len(b) > 1 and k % 8 == 0 else None
        cols = [own.column(c).combine_chunks() for c in ("doc_id", "piece", "start", "length", "ids_crc32")]
        return pa.table([*cols, pa.array(seq, pa.int64()), pa.array(off, pa.int64()), pa.array(fill, pa.int32()), pa.array(lead, pa.bool_()), pa.array(shape, pa.list_(pa.int32()))], names=_NAMES)

    return run


_NAMES = ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset", "filled", "lead", "lengths"]


def _none() -> pa.Table:
    kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.bool_(), pa.list_(pa.int32())]
    return pa.table([pa.array([], k) for k in kinds], names=_NAMES)


def packed(parts: DataFrame, limit: int = SEQUENCE, island: int = ISLAND, turns: int = 3) -> DataFrame:
    """pieces() rows with sequence_id and offset."""
    left, done = settle(parts, "pieces"), []
    keys = ["doc_id", "piece", "start", "length", "ids_crc32"]
    elite = None
    for turn in range(turns):
        n = left.count()
        if not n:
            break
        islands = -(-n // island)
        # Dealt by row, not by key: repeated rows spread evenly too.
        items = left.select(*keys, F.lit(0).alias("mark"), F.lit(None).cast("array<int>").alias("lengths"), F.pmod(F.xxhash64(F.monotonically_increasing_id(), F.lit(turn)), F.lit(islands)).alias("island"))
        if elite is not None:
            # Each elite pattern visits one island of the next turn.
            visit = elite.select(*[F.lit(None).cast(t).alias(c) for c, t in zip(keys, ("long", "int", "long", "int", "long"), strict=True)], F.lit(1).alias("mark"), "lengths", F.pmod(F.xxhash64("sequence_id"), F.lit(islands)).alias("island"))
            items = items.unionByName(visit)
        got = settle(items.groupBy("island").applyInArrow(_island(limit, turn), _PACKED), "packed")
        last = turn == turns - 1 or islands == 1
        done.append(got if last else got.where(F.col("filled") >= limit - turn))
        if last:
            break
        left, elite = got.where(F.col("filled") < limit - turn), got.where("lengths is not null").select("sequence_id", "lengths")
    out = done[0] if done else left.select(*keys, F.lit(0).cast("long").alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    for d in done[1:]:
        out = out.unionByName(d)
    return out.select("doc_id", "piece", "start", F.col("length").cast("long").alias("length"), "ids_crc32", "sequence_id", "offset")


def op3_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return packed(pieces(documents(spark, sf_dir, "doc_id", "text"), str(public_tokenizers.path("byte_bpe_50k.json"))))
