"""Array kernels that run inside one task: codes, block distances, edge selection, beam search, graph construction."""
from __future__ import annotations

import numpy as np


def pack(bits: np.ndarray) -> np.ndarray:
    """(n, D) booleans to (n, W) words."""
    n, d = bits.shape
    pad = np.zeros((n, -(-d // 64) * 64), np.uint8)
    pad[:, :d] = bits
    return np.packbits(pad, axis=1, bitorder="little").view(np.uint64)


def sm_codes(x: np.ndarray, tau: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sign plane, strength plane, threshold; strict comparisons."""
    x = np.asarray(x, np.float64)
    tau = np.abs(x).mean(1) if tau is None else tau
    return pack(x > 0), pack(np.abs(x) > tau[:, None]), tau


def levels(x: np.ndarray) -> np.ndarray:
    x = np.asarray(x, np.float64)
    return np.where(x > 0, 1, -1) * (1 + (np.abs(x) > np.abs(x).mean(1)[:, None]))


def bq_block(ya: np.ndarray, yb: np.ndarray) -> np.ndarray:
    """All distances of two blocks of levels: (<|a|,|b|> - <a,b>) / 2, two matrix products."""
    a, b = ya.astype(np.float32), yb.astype(np.float32)
    return np.rint((np.abs(a) @ np.abs(b).T - a @ b.T) / 2).astype(np.int32)


def unpack_levels(p: np.ndarray, s: np.ndarray, dim: int) -> np.ndarray:
    """Signed levels of planes."""
    bits = [np.unpackbits(np.ascontiguousarray(v).view(np.uint8).reshape(len(v), -1), axis=1, bitorder="little")[:, :dim].astype(np.float64) for v in (p, s)]
    return (2 * bits[0] - 1) * (1 + bits[1])


def _counted(pa: np.ndarray, pb: np.ndarray, strong: tuple[np.ndarray, np.ndarray] | None) -> np.ndarray:
    """Differing signs of two planes (words last), each weighted by the strong bits of both sides if these are given."""
    kind = np.uint16 if 256 * pa.shape[-1] < 1 << 16 else np.int64  # a word adds 256 at most
    out = 0
    for w in range(pa.shape[-1]):
        x = pa[..., w] ^ pb[..., w]
        out = out + np.bitwise_count(x).astype(kind)
        if strong is not None:
            xs, t = x & strong[0][..., w], strong[1][..., w]
            out += np.bitwise_count(xs)
            out += np.bitwise_count(x & t)
            out += np.bitwise_count(xs & t)
    return out.astype(np.int64)


class Metric:
    """Distances between a batch of query codes and rows of base codes. Queries and base share the class."""

    def __init__(self, kind: str, **arrays):
        self.kind, self.a = kind, arrays
        self.n = len(next(iter(arrays.values())))

    @classmethod
    def of(cls, kind: str, x: np.ndarray, **more) -> Metric:
        x = np.asarray(x, np.float64)
        if kind in ("bq2", "bq1"):
            p, s, _ = sm_codes(x)
            return cls(kind, p=p, s=s) if kind == "bq2" else cls(kind, p=p)
        if kind == "sq2":
            lo, hi = more.get("span") or (x.min(), x.max())
            return cls(kind, c=np.clip(np.floor((x - lo) * 4 / max(hi - lo, 1e-12)), 0, 3).astype(np.int16))
        if kind in ("float", "adc", "pq"):
            n = np.linalg.norm(x, axis=1, keepdims=True)
            unit = x / np.where(n > 0, n, 1)
            if kind == "float":
                return cls(kind, x=unit)
            if kind == "adc":
                return cls(kind, x=unit, y=levels(x).astype(np.float64))
            book = more["book"]
            return cls(kind, x=unit, r=pq_decode(pq_encode(unit, book), book))
        raise ValueError(kind)

    @classmethod
    def of_planes(cls, kind: str, p: np.ndarray, s: np.ndarray, dim: int) -> Metric:
        """Base rows from stored planes alone: no float is read."""
        if kind == "bq2":
            return cls(kind, p=p, s=s)
        if kind == "bq1":
            return cls(kind, p=p)
        if kind == "adc":
            return cls(kind, y=unpack_levels(p, s, dim))
        raise ValueError(f"{kind} does not navigate on planes")

    @classmethod
    def of_codes(cls, kind: str, c: np.ndarray, **more) -> Metric:
        """Base rows from stored byte codes: 'sq2' bucket numbers, 'pq' cell numbers."""
        if kind == "sq2":
            return cls(kind, c=c.astype(np.int16))
        return cls(kind, r=pq_decode(c, more["book"]))

    @classmethod
    def joined(cls, a: Metric, b: Metric) -> Metric:
        return cls(a.kind, **{k: np.concatenate([a.a[k], b.a[k]]) for k in a.a})

    def take(self, rows: np.ndarray) -> Metric:
        return Metric(self.kind, **{k: v[rows] for k, v in self.a.items()})

    def to(self, base: Metric, ids: np.ndarray) -> np.ndarray:
        """Distances of query i to base rows ids[i, :]."""
        a, b = self.a, base.a
        if self.kind in ("bq2", "bq1"):
            strong = (a["s"][:, None, :], b["s"][ids]) if self.kind == "bq2" else None
            return _counted(a["p"][:, None, :], b["p"][ids], strong)
        if self.kind == "sq2":
            return np.abs(a["c"][:, None, :] - b["c"][ids]).sum(-1, dtype=np.int64)
        if self.kind == "float":
            v = 1 - np.einsum("bd,brd->br", a["x"], b["x"][ids])
        elif self.kind == "adc":
            v = -np.einsum("bd,brd->br", a["x"], b["y"][ids])
        else:
            v = 1 - np.einsum("bd,brd->br", a["x"], b["r"][ids])
        return np.rint(v * (1 << 30)).astype(np.int64)  # integers, so that ties go by id everywhere

    def cross(self, base: Metric) -> np.ndarray:
        """Distances of every query to every base row; whole-number codes by matrix products, which stay exact in single precision."""
        a, b = self.a, base.a
        if self.kind in ("bq2", "bq1"):
            one = lambda m: unpack_levels(m["p"], m["s"] if self.kind == "bq2" else np.zeros_like(m["p"]), 64 * m["p"].shape[1])
            return bq_block(one(a), one(b)).astype(np.int64)  # bits beyond the dimension have equal signs: they add nothing
        if self.kind == "sq2":
            over = lambda c: np.concatenate([c >= k for k in (1, 2, 3)], 1).astype(np.float32)
            x, y = over(a["c"]), over(b["c"])
            return np.rint(x.sum(1)[:, None] + y.sum(1)[None] - 2 * (x @ y.T)).astype(np.int64)
        return np.concatenate([self.take(np.array([i])).to(base, np.arange(base.n)[None]) for i in range(self.n)]) if self.n else np.zeros((0, base.n), np.int64)

    def within(self, ids: np.ndarray) -> np.ndarray:
        """(b, r, r): distances among the rows ids[i, :] of each i; [i, j, k] has j as base row and k as query."""
        a = self.a
        if self.kind in ("bq2", "bq1"):
            p, s = a["p"][ids], a["s"][ids] if self.kind == "bq2" else None
            return _counted(p[:, :, None], p[:, None], None if s is None else (s[:, :, None], s[:, None]))
        if self.kind == "sq2":
            c = a["c"][ids]
            return np.abs(c[:, :, None] - c[:, None]).sum(-1, dtype=np.int64)
        x = a["x"][ids]
        v = np.einsum("bid,bjd->bij", x if self.kind == "float" else a["y" if self.kind == "adc" else "r"][ids], x)
        return np.rint(((0 if self.kind == "adc" else 1) - v) * (1 << 30)).astype(np.int64)

    def beside(self, one: np.ndarray, ids: np.ndarray) -> np.ndarray:
        """(b, r): what within() has in the row of ids[i, one[i]], for codes of whole numbers; that row alone is computed."""
        return self.take(ids[np.arange(len(ids)), one]).to(self, ids)

    def among(self, rows: np.ndarray) -> np.ndarray:
        own = self.take(rows)
        return own.to(own, np.broadcast_to(np.arange(len(rows)), (len(rows), len(rows))))


def select_edges(d: np.ndarray, ids: np.ndarray, among: np.ndarray, most: int, alpha100: int, ties: str = "id", cover: np.ndarray | None = None, fine: np.ndarray | None = None, refill: bool = False) -> list[int]:
    """Places of kept candidates, nearest first: one is kept when no kept one is so near to it that alpha times their distance is
    below its distance to the target. Compared in hundredths, in integers.

    refill: where fewer than `most` are kept, the nearest of the others fill the list.
    ties: 'id'; 'coverage' takes, among equal distances, the one that disagrees in most bits not covered so far (cover: words of
    disagreement); 'adc' orders equal distances by fine."""
    order = np.lexsort((ids, fine, d)) if ties == "adc" else np.lexsort((ids, d))
    open_ = np.ones(len(d), bool)
    kept: list[int] = []
    seen = np.zeros(cover.shape[1], np.uint64) if ties == "coverage" else None
    k = 0
    while k < len(order) and len(kept) < most:
        if ties == "coverage":
            same = [i for i in order[k:] if d[i] == d[order[k]]]
            live = [i for i in same if open_[i]]
            k += len(same)
            while live and len(kept) < most:
                gain = [int(np.bitwise_count(cover[i] & ~seen).sum()) for i in live]
                i = live.pop(int(np.argmax(gain)))
                kept.append(int(i))
                seen |= cover[i]
                open_ &= 100 * d <= alpha100 * among[:, i]
                live = [j for j in live if open_[j]]
            continue
        i = order[k]
        k += 1
        if open_[i]:
            kept.append(int(i))
            open_ &= 100 * d <= alpha100 * among[:, i]
    if refill and len(kept) < most:
        have = set(kept)
        kept += [int(i) for i in order if int(i) not in have][: most - len(kept)]
    return kept


#: Words of the distances among candidates that a step of edge selection holds.
AMONG = 1 << 21


def chosen(base: Metric, t: np.ndarray, ids: np.ndarray, d: np.ndarray, most: int, alpha100: int, ties: str = "id", fine: Metric | None = None, refill: bool = False, full: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """select_edges for many targets: ids (padded by -1) and d of each in order of (d, id) give neighbours and distances, padded by
    -1 and 0. full: rows that hold at most `most` candidates keep them all."""
    out, od = np.full((len(t), most), -1, np.int64), np.zeros((len(t), most), np.int64)
    one = next(iter(base.a.values()))
    lazy = base.kind in ("bq2", "bq1", "sq2")  # symmetric and whole: only the distances to kept candidates are computed
    step = max(1, AMONG // (ids.shape[1] * (16 if lazy else ids.shape[1]) * (one.shape[1] if base.kind == "sq2" else 1)))
    for lo in range(0, len(t), step):
        i, e, at = ids[lo : lo + step], d[lo : lo + step], t[lo : lo + step]
        have = i >= 0
        safe = np.maximum(i, 0)
        if ties == "adc":
            o = np.lexsort((i, fine.take(at).to(fine, safe), np.where(have, e, np.int64(1) << 50)), axis=1)
            i, e, have, safe = (np.take_along_axis(v, o, 1) for v in (i, e, have, safe))
        among = None if lazy else base.within(safe)
        least_far = -(-100 * e // alpha100)  # 100 e <= alpha100 x holds from this x on
        cover = base.a["p"][safe] ^ base.a["p"][at][:, None] if ties == "coverage" else None
        seen = np.zeros((len(at), cover.shape[2]), np.uint64) if cover is not None else None
        every, open_, line = np.arange(len(at)), have.copy(), np.arange(len(at))
        used = np.zeros_like(have)
        count = np.zeros(len(at), np.int64)
        for _ in range(most):
            if cover is None:
                pick = open_.argmax(1)
            else:  # among the nearest, the one that covers most
                least = np.where(open_, e, np.int64(1) << 50).min(1)
                gain = np.bitwise_count(cover & ~seen[:, None]).sum(-1, dtype=np.int64)
                pick = np.where(open_ & (e == least[:, None]), gain, -1).argmax(1)
            live = open_[every, pick]
            line = every[live]
            if not len(line):
                break
            pick = pick[live]
            out[lo + line, count[line]], od[lo + line, count[line]] = i[line, pick], e[line, pick]
            count[line] += 1
            used[line, pick] = True
            if cover is not None:
                seen[line] |= cover[line, pick]
            if len(line) == len(at):
                open_ &= least_far <= (base.beside(pick, safe) if lazy else among[line, pick])
            else:
                open_[line] &= least_far[line] <= (base.beside(pick, safe[line]) if lazy else among[line, pick])
            open_[line, pick] = False
        if refill or full:
            rest = have & ~used
            rest &= (np.cumsum(rest, 1) <= (most - count)[:, None]) & (refill | (have.sum(1) <= most))[:, None]
            r, c = np.nonzero(rest)
            spot = count[r] + (np.cumsum(rest, 1) - 1)[r, c]
            out[lo + r, spot], od[lo + r, spot] = i[r, c], e[r, c]
    return out, od


def reached(nbrs: np.ndarray, entry: np.ndarray) -> np.ndarray:
    """Mask of the nodes that paths from the entries meet."""
    seen = np.zeros(len(nbrs), bool)
    front = np.unique(entry)
    seen[front] = True
    while len(front):
        new = nbrs[front].ravel()
        front = np.unique(new[new >= 0])
        front = front[~seen[front]]
        seen[front] = True
    return seen


def _swept(base: Metric, nbrs: np.ndarray, queries: Metric, entry: np.ndarray, ef: int, cached: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The beam whose pool holds all nodes: it drops none, so it expands every node that can be reached, in whatever order, and ends
    with all of them ranked. The graph is walked once for the batch."""
    got = np.flatnonzero(reached(nbrs, entry))
    d = queries.cross(base.take(got))
    bits = base.n.bit_length()
    key = (d << bits) | got
    key.sort(1)
    work = np.empty((queries.n, 4), np.int64)
    work[:, :3] = len(got)
    work[:, 3] = len(got) if cached is None else (~cached[got]).sum()
    pad = ((0, 0), (0, ef - key.shape[1]))
    return np.pad(key & ((1 << bits) - 1), pad, constant_values=-1), np.pad(key >> bits, pad, constant_values=1 << 50), work


def beam(base: Metric, nbrs: np.ndarray, queries: Metric, entry: np.ndarray, ef: int, width: int = 1, limit: int | None = None, cached: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Best-first search of a batch of queries on one graph. Returns ids and distances of the pools (padded by -1 and a huge
    distance), and work: evaluations, expanded nodes, rounds and reads of each query; a read is an expanded node that is not cached.

    entry: nodes where every query starts, or a row of nodes for each query.
    A place of a pool is one number, distance before id before a bit that tells whether the node is expanded: pools are kept in
    order by a plain sort."""
    b, n = queries.n, limit or base.n
    entry = np.asarray(entry)[..., :ef]
    if width == 1 and ef >= n and (entry.ndim == 1 or (entry == entry[:1]).all()):
        return _swept(base, nbrs, queries, entry, ef, cached)
    bits, free = n.bit_length() + 1, np.iinfo(np.int64).max
    mask = (1 << bits) - 2
    pool = np.full((b, ef), free)
    seen = np.zeros((b, n), bool)
    k = entry.shape[-1]
    start = np.broadcast_to(entry, (b, k))
    pool[:, :k] = (queries.to(base, start) << bits) | (start << 1)
    pool.sort(1)
    np.put_along_axis(seen, start, True, 1)
    work = np.zeros((b, 4), np.int64)
    work[:, 0] = k
    rows, now = np.arange(b), pool
    while len(rows):
        fresh = (now & 1) == 0
        pick = fresh.argmax(1)[:, None] if width == 1 else np.argsort(~fresh, 1, kind="stable")[:, :width]
        valid = np.take_along_axis(fresh, pick, 1)
        live = valid[:, 0]
        if not live.all():
            pool[rows[~live]] = now[~live]
            rows, now, pick, valid = rows[live], now[live], pick[live], valid[live]
            if not len(rows):
                break
        best = np.take_along_axis(now, pick, 1)
        src = np.where(valid, (best & mask) >> 1, -1)
        np.put_along_axis(now, pick, best | 1, 1)
        work[rows, 1] += valid.sum(1)
        work[rows, 2] += 1
        work[rows, 3] += (valid if cached is None else valid & ~cached[np.maximum(src, 0)]).sum(1)
        new = np.where((src >= 0)[:, :, None], nbrs[src], -1).reshape(len(rows), -1)
        ok = (new >= 0) & ~seen[rows[:, None], np.maximum(new, 0)]
        if width > 1:  # two expanded nodes may name the same neighbour
            o = np.argsort(new, 1, kind="stable")
            s = np.take_along_axis(new, o, 1)
            dup = np.zeros_like(ok)
            np.put_along_axis(dup, o[:, 1:], s[:, 1:] == s[:, :-1], 1)
            ok &= ~dup
        r, c = np.nonzero(ok)
        if not len(r):
            continue
        at = new[r, c]
        seen[rows[r], at] = True
        work[rows, 0] += ok.sum(1)
        more = np.full(new.shape, free)
        more[r, c] = (queries.take(rows[r]).to(base, at[:, None])[:, 0] << bits) | (at << 1)
        now = np.sort(np.concatenate([now, more], 1), 1)[:, :ef]
    none = pool == free
    return np.where(none, -1, (pool & mask) >> 1), np.where(none, np.int64(1) << 50, pool >> bits), work


def schedule(n: int, batch: str) -> list[int]:
    """Ends of the batches in which nodes are linked."""
    if batch == "sequential":
        return list(range(1, n + 1))
    if batch.startswith("chunk:"):
        step = int(batch.split(":")[1])
        return [1, *range(1 + step, n, step), n] if n > 1 else [n]
    out, at = [], 1
    while at < n:
        out.append(at)
        at = min(at * 2, at + 512)
    return [*out, n]


def near_entry(nbrs: np.ndarray, entry: int, most: int) -> np.ndarray:
    """Mask of the first `most` nodes in breadth-first order from the entry: the nodes that a cache would hold."""
    held = np.zeros(len(nbrs), bool)
    front = np.array([entry])
    held[front] = True
    left = most - 1
    while len(front) and left > 0:
        new = np.unique(nbrs[front])
        new = new[(new >= 0)]
        front = new[~held[new]][:left]
        held[front] = True
        left -= len(front)
    return held


def link(base: Metric, m: int, ef_c: int, alpha100: int, batch: str = "doubling", ties: str = "id", fine: Metric | None = None, grown: tuple[np.ndarray, np.ndarray] | None = None, refill: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """A graph on rows 0..n-1 in this order: neighbours (n, 2m; padded by -1) and distances. Each batch searches the graph as it
    was before it, selects edges, and then gathers the reverse edges by destination; full nodes are selected anew.

    grown: neighbours and distances of the first rows, an existing graph; only the rows behind it are linked."""
    n, most = base.n, 2 * m
    nbrs, nd = np.full((n, most), -1, np.int64), np.zeros((n, most), np.int64)
    done = 0
    if grown is not None:
        done = len(grown[0])
        nbrs[:done, : grown[0].shape[1]], nd[:done, : grown[0].shape[1]] = grown

    for end in schedule(n, batch):
        if end <= done:
            continue
        new = np.arange(done, end)
        if not done:
            done = end
            continue
        got, gd, _ = beam(base, nbrs, base.take(new), np.array([0]), ef_c, limit=n)
        nbrs[new], nd[new] = chosen(base, new, got, gd, most, alpha100, ties, fine, refill)
        r, c = np.nonzero(nbrs[new] >= 0)
        to, by, d = nbrs[new][r, c], new[r], nd[new][r, c]
        # Each named node: its own neighbours and those that named it.
        names = np.unique(to)
        own_r, own_c = np.nonzero(nbrs[names] >= 0)
        t = np.concatenate([names[own_r], to])
        ids, d = np.concatenate([nbrs[names][own_r, own_c], by]), np.concatenate([nd[names][own_r, own_c], d])
        o = np.lexsort((ids, d, t))
        t, ids, d = t[o], ids[o], d[o]
        first = np.searchsorted(t, names)
        size = np.diff(np.append(first, len(t)))
        place = np.arange(len(t)) - np.repeat(first, size)
        width = np.maximum(most, 1 << np.ceil(np.log2(np.maximum(size, 1))).astype(int))
        for w in np.unique(width).tolist():
            mine = width == w
            rows = np.repeat(mine, size)
            wide_i, wide_d = np.full((mine.sum(), w), -1, np.int64), np.zeros((mine.sum(), w), np.int64)
            line = np.repeat(np.arange(mine.sum()), size[mine])
            wide_i[line, place[rows]], wide_d[line, place[rows]] = ids[rows], d[rows]
            nbrs[names[mine]], nd[names[mine]] = (wide_i, wide_d) if w == most else chosen(base, names[mine], wide_i, wide_d, most, alpha100, ties, fine, refill, full=True)
        done = end
    return nbrs, nd


def connected(base: Metric, nbrs: np.ndarray, nd: np.ndarray, ef: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """The graph with a path from the first node to every other: a node that no path meets is named by the nearest node that has one
    and a free place, of all such nodes (ef, the width of an earlier search for it, is not used). No edge goes, so nothing else is
    lost; where every place is taken, the rest stays as it is."""
    seen = reached(nbrs, np.array([0])) if len(nbrs) else np.zeros(0, bool)
    free = (nbrs < 0).any(1)
    for u in np.flatnonzero(~seen).tolist():
        if seen[u]:
            continue
        can = np.flatnonzero(seen & free)
        if not len(can):
            break  # and so it stays
        d = base.take(np.array([u])).to(base, can[None])[0]
        at = d.argmin()
        v = can[at]
        spot = (nbrs[v] < 0).argmax()
        nbrs[v, spot], nd[v, spot] = u, d[at]
        o = np.lexsort((nbrs[v], nd[v], nbrs[v] < 0))
        nbrs[v], nd[v] = nbrs[v][o], nd[v][o]
        free[v] = (nbrs[v] < 0).any()
        front = np.array([u])
        while len(front):  # what u leads to
            seen[front] = True
            new = nbrs[front].ravel()
            new = np.unique(new[new >= 0])
            front = new[~seen[new]]
    return nbrs, nd


def repair(base: Metric, nbrs: np.ndarray, nd: np.ndarray, gone: np.ndarray, m: int, alpha100: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The graph without the nodes of a mask: a node that loses neighbours selects anew among those it keeps and the neighbours of
    those it loses. Returns (places that stay, neighbours, distances) with places counted anew."""
    most = 2 * m
    nbrs, nd = nbrs.copy(), nd.copy()
    hurt = np.flatnonzero(~gone & ((nbrs >= 0) & gone[np.maximum(nbrs, 0)]).any(1))
    fresh = {}
    for t in hurt.tolist():
        own = nbrs[t][nbrs[t] >= 0]
        cand = np.unique(np.concatenate([own, nbrs[own[gone[own]]].ravel()]))
        cand = cand[(cand >= 0) & (cand != t)]
        cand = cand[~gone[cand]]
        d = base.take(np.array([t])).to(base, cand[None, :])[0] if len(cand) else np.zeros(0, np.int64)
        kept = select_edges(d, cand, base.among(cand), most, alpha100) if len(cand) else []
        fresh[t] = (cand[kept], d[kept])
    for t, (ids, d) in fresh.items():
        nbrs[t], nd[t] = -1, 0
        nbrs[t, : len(ids)], nd[t, : len(ids)] = ids, d
    stay = np.flatnonzero(~gone)
    place = np.full(len(gone), -1, np.int64)
    place[stay] = np.arange(len(stay))
    out = nbrs[stay]
    return stay, np.where(out >= 0, place[np.maximum(out, 0)], -1), nd[stay]


# -- product codes ------------------------------------------------------------------------------------------------------


def nearest(x: np.ndarray, c: np.ndarray, step: int = 1024) -> np.ndarray:
    """The nearest row of c for each row of x, a few rows at a time: their products stay in the cache."""
    n, turned = (c * c).sum(1)[None, :], c.T * 2
    return np.concatenate([np.argmin(n - x[lo : lo + step] @ turned, 1) for lo in range(0, len(x), step)] or [np.zeros(0, np.int64)])


def kmeans(x: np.ndarray, k: int, rounds: int = 12, seed: int = 42) -> np.ndarray:
    r = np.random.default_rng(seed)
    k = min(k, len(x))
    c = x[r.permutation(len(x))[:k]].copy()
    for _ in range(rounds):
        a = nearest(x, c)
        n = np.bincount(a, minlength=k)
        s = np.stack([np.bincount(a, x[:, j], k) for j in range(x.shape[1])], 1)
        c = np.where(n[:, None] > 0, s / np.maximum(n, 1)[:, None], c)
    return c


def pq_fit(x: np.ndarray, parts: int, cells: int = 256, seed: int = 42) -> np.ndarray:
    d = x.shape[1] // parts
    books = [kmeans(np.ascontiguousarray(x[:, i * d : (i + 1) * d]), cells, seed=seed + i) for i in range(parts)]
    full = max(len(b) for b in books)
    return np.stack([np.pad(b, ((0, full - len(b)), (0, 0)), constant_values=1e6) for b in books])


def pq_encode(x: np.ndarray, book: np.ndarray) -> np.ndarray:
    d = book.shape[2]
    return np.stack([nearest(x[:, i * d : (i + 1) * d], b) for i, b in enumerate(book)], 1).astype(np.uint8)


def pq_decode(c: np.ndarray, book: np.ndarray) -> np.ndarray:
    return np.concatenate([book[i][c[:, i]] for i in range(len(book))], 1)


def opq_fit(x: np.ndarray, parts: int, rounds: int = 6, cells: int = 256, seed: int = 42) -> tuple[np.ndarray, np.ndarray]:
    """A rotation and books: alternately fit books and turn the data towards their reconstruction."""
    r = np.eye(x.shape[1])
    for _ in range(rounds):
        book = pq_fit(x @ r, parts, cells, seed)
        u, _, v = np.linalg.svd(x.T @ pq_decode(pq_encode(x @ r, book), book))
        r = u @ v
    return r, pq_fit(x @ r, parts, cells, seed)


def rotation(dim: int, seed: int) -> np.ndarray:
    q, r = np.linalg.qr(np.random.default_rng(seed).normal(size=(dim, dim)))
    return q * np.sign(np.diag(r))
