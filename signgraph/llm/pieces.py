"""SentencePiece encoding and decoding by suffix-array matching.

Texts are cut into units (a run of spaces and what follows up to the next). The units that a worker has not met are laid end
to end and indexed by a suffix array; every piece of the vocabulary is searched in it by binary search, all pieces at once;
the occurrence ranges give edges (place, length, piece), sorted by place. Relaxation then contracts edges from single
characters on: in each round every unit contracts the best-scored edge whose halves are its present tokens, the leftmost
among equals, which is the order of the model's own merges. Characters without a piece fall back to byte pieces.

Null and empty texts have no ids and decode to the empty text. Repeated rows get equal results. Extra columns are ignored.
"""
from __future__ import annotations

import hashlib
import heapq
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bytescan import prefix_sums, span_hash
from .common import blocks, documents, text_view
from .suffix import suffix_order

MARK = 0x2581  # stands for a space
HELD = 1_500_000
ROUND = 48  # tokens of a unit that is contracted with others; longer ones go by a heap


class Vocabulary:
    """Pieces of a model file; normal ones sorted by bytes."""

    def __init__(self, path: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        self.bytes_ = np.full(256, sp.unk_id(), np.uint32)
        out, raw = [b""] * n, []
        for i in range(n):
            p = sp.id_to_piece(i)
            if sp.is_byte(i):
                out[i] = bytes([int(p[3:-1], 16)])
                self.bytes_[out[i][0]] = i
            elif not (sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)):
                out[i] = p.replace("▁", " ").encode()
                raw.append((p.encode(), i))
        self.ids = np.array([i for _, i in raw], np.int64)
        self.size = np.array([len(p) for p, _ in raw], np.int64)
        self.reach = -(-int(self.size.max()) // 8) * 8  # bytes that a search compares: whole words, up to the longest piece
        self.wide = 1 << (self.reach + 1).bit_length()
        self.score = np.array([sp.get_score(int(i)) for i in self.ids])
        self.low = np.frombuffer(b"".join(p.ljust(self.reach, b"\0") for p, _ in raw), ">u8").reshape(len(raw), -1).astype(np.uint64)
        self.high = np.frombuffer(b"".join(p.ljust(self.reach, b"\xff") for p, _ in raw), ">u8").reshape(len(raw), -1).astype(np.uint64)
        self.out_size = np.array([len(p) for p in out], np.int64)
        self.out_at = np.cumsum(self.out_size) - self.out_size
        self.out = np.frombuffer(b"".join(out), np.uint8)

    def occurrences(self, text: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Edges of text (units that end in 255), sorted: place * self.wide + length, and the piece's row."""
        sa, _ = suffix_order(text, self.reach)
        pad = np.concatenate([text, np.full(self.reach + 8, 255, np.uint8)])
        word = np.zeros(len(text) + self.reach, np.uint64)
        for k in range(8):
            word = word << np.uint64(8) | pad[k : k + len(word)]

        def search(key: np.ndarray, after: bool) -> np.ndarray:
            lo, hi = np.zeros(len(key), np.int64), np.full(len(key), len(sa))
            while (lo < hi).any():
                mid = (lo + hi) // 2
                at = sa[np.minimum(mid, len(sa) - 1)].astype(np.int64)
                less, open_ = np.zeros(len(key), bool), np.arange(len(key))
                for c in range(self.reach // 8):
                    w, k = word[at[open_] + 8 * c], key[open_, c]
                    less[open_[w < k]] = True
                    open_ = open_[w == k]
                    if not len(open_):
                        break
                if after:
                    less[open_] = True
                go = lo < hi
                lo, hi = np.where(go & less, mid + 1, lo), np.where(go & ~less, mid, hi)
            return lo

        first, last = search(self.low, False), search(self.high, True)
        count = last - first
        row = np.repeat(np.arange(len(count)), count)
        place = sa[np.repeat(first - (np.cumsum(count) - count), count) + np.arange(int(count.sum()))].astype(np.int64)
        key = place * self.wide + self.size[row]
        order = np.argsort(key)
        return key[order], row[order]

    def relax(self, text: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all units of text end to end, and how many each unit has."""
        key, row = self.occurrences(text)

        def edge(s: np.ndarray, e: np.ndarray) -> np.ndarray:
            want = s * self.wide + np.minimum(e - s, self.wide - 1)
            k = np.minimum(np.searchsorted(key, want), max(0, len(key) - 1))
            return np.where(key[k] == want, row[k], -1) if len(key) else np.full(len(s), -1)

        stop = np.flatnonzero(text == 255)
        lead = np.flatnonzero((text != 255) & ((text & 0xC0) != 0x80))  # starts of characters
        unit = np.searchsorted(stop, lead)
        many = np.bincount(unit, minlength=len(stop))
        live = np.ones(len(lead), bool)  # a token starts here
        for u in np.flatnonzero(many > ROUND).tolist():
            self._heap(np.arange(np.searchsorted(unit, u), np.searchsorted(unit, u, "right")), lead, int(stop[u]), key, row, live)
        act = np.flatnonzero((many[unit] <= ROUND) & (many[unit] > 1))
        while len(act):
            s, u = lead[act], unit[act]
            e = np.append(s[1:], 0)
            final = np.append(u[1:] != u[:-1], True)
            e[final] = stop[u[final]]
            pair_end = np.append(e[1:], 0)
            r = np.where(final, -1, edge(s, np.where(final, s, pair_end)))
            score = np.where(r >= 0, self.score[r], -np.inf)
            first = np.flatnonzero(np.append(True, u[1:] != u[:-1]))
            best = np.repeat(np.maximum.reduceat(score, first), np.diff(np.append(first, len(u))))
            hit = np.flatnonzero((score == best) & (r >= 0))
            hit = hit[np.append(True, u[hit][1:] != u[hit][:-1])] if len(hit) else hit
            live[act[hit + 1]] = False
            keep = (best > -np.inf)
            keep[hit + 1] = False
            act = act[keep]
        at = np.flatnonzero(live)
        s, u = lead[at], unit[at]
        e = np.append(s[1:], 0)
        final = np.append(u[1:] != u[:-1], True)
        e[final] = stop[u[final]]
        r = edge(s, e)
        size = np.where(r >= 0, 1, e - s)
        end = np.cumsum(size)
        ids = np.empty(int(end[-1]) if len(end) else 0, np.uint32)
        known = r >= 0
        ids[(end - size)[known]] = self.ids[r[known]]
        for k in range(4):
            more = ~known & (size > k)
            ids[(end - size)[more] + k] = self.bytes_[text[s[more] + k]]
        return ids, np.bincount(u, size, len(stop)).astype(np.int64)

    def _heap(self, chars, lead, stop, key, row, live) -> None:
        """Contract one long unit by a queue of its edges."""
        s = lead[chars].tolist()
        n = len(s)
        nxt, prev, end = list(range(1, n + 1)), list(range(-1, n - 1)), [*s[1:], stop]
        gone, heap = [False] * n, []
        keys = key[np.searchsorted(key, s[0] * self.wide) : np.searchsorted(key, (stop + 1) * self.wide)]
        base = int(np.searchsorted(key, s[0] * self.wide))
        score = dict(zip(keys.tolist(), self.score[row[base : base + len(keys)]].tolist(), strict=True))

        def push(i: int) -> None:
            j = nxt[i]
            if i >= 0 and j < n and end[j] - s[i] < self.wide and (v := score.get(s[i] * self.wide + end[j] - s[i])) is not None:
                heapq.heappush(heap, (-v, i, end[j]))

        for i in range(n):
            push(i)
        while heap:
            _, i, e = heapq.heappop(heap)
            if gone[i] or nxt[i] >= n or end[nxt[i]] != e:
                continue
            j = nxt[i]
            gone[j], end[i], nxt[i] = True, end[j], nxt[j]
            if nxt[i] < n:
                prev[nxt[i]] = i
            live[chars[j]] = False
            push(i)
            if prev[i] >= 0:
                push(prev[i])

    def decode(self, ids: np.ndarray) -> bytes:
        size = self.out_size[ids]
        end = np.cumsum(size)
        raw = self.out[np.repeat(self.out_at[ids] - (end - size), size) + np.arange(int(end[-1]) if len(end) else 0)].tobytes()
        return raw[1:] if raw[:1] == b" " else raw


class Encoder:
    """Ids of texts; units met before are looked up."""

    def __init__(self, path: str):
        self.vocabulary = Vocabulary(path)
        self.forget()

    def forget(self) -> None:
        self.keys, self.start, self.count = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.ids, self.used = np.zeros(1 << 20, np.uint32), 0

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        x = np.frombuffer("".join("▁" + t if t else "" for t in texts).encode("utf-32-le", "surrogatepass"), np.uint32).copy()
        offs = np.concatenate([[0], np.cumsum([len(t) + 1 if t else 0 for t in texts])])
        if not len(x):
            return [np.zeros(0, np.uint32) for _ in texts]
        x[x == 32] = MARK
        mark = x == MARK
        first = np.zeros(len(x) + 1, bool)
        first[offs] = True
        start = mark.copy()
        start[1:] &= ~mark[:-1] | first[1 : len(x)]
        start |= first[: len(x)]
        s = np.flatnonzero(start)
        e = np.append(s[1:], len(x))
        h, at, back = np.unique(span_hash(prefix_sums(x), s, e), return_index=True, return_inverse=True)
        if len(self.keys) > HELD:
            self.forget()
        place = np.searchsorted(self.keys, h)
        known = self.keys[np.minimum(place, len(self.keys) - 1)] == h if len(self.keys) else np.zeros(len(h), bool)
        new = np.flatnonzero(~known)
        if len(new):
            raw = x.tobytes()
            units = b"".join(str(raw[4 * i : 4 * j], "utf-32-le", "surrogatepass").encode("utf-8", "surrogatepass") + b"\xff" for i, j in zip(s[at[new]].tolist(), e[at[new]].tolist(), strict=True))
            flat, size = self.vocabulary.relax(np.frombuffer(units, np.uint8))
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
        return [ids[edge[i] : edge[i + 1]] for i in range(len(texts))]


_ENCODERS: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    if path not in _ENCODERS:
        _ENCODERS[path] = Encoder(path)
    return _ENCODERS[path]


def _run(path: str):
    def run(batches):
        enc = encoder(path)
        for b in batches:
            data, offs = text_view(b.column(1))
            raw = data.tobytes()
            for lo, hi in blocks(offs, 4 << 20):
                got = enc.encode([raw[offs[i] : offs[i + 1]].decode() for i in range(lo, hi)])
                back = [enc.vocabulary.decode(g) for g in got]
                edge = np.concatenate([[0], np.cumsum([len(g) for g in got])]).astype(np.int32)
                ids = pa.ListArray.from_arrays(pa.array(edge), pa.array(np.concatenate(got).astype(np.int32)))
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), pa.array([len(g) for g in got], pa.int64()), pa.array([zlib.crc32(g.astype("<u4").tobytes()) for g in got], pa.int64()), pa.array([hashlib.sha256(t).hexdigest() for t in back]), pa.array([t == raw[offs[lo + k] : offs[lo + k + 1]] for k, t in enumerate(back)]), ids], names=["doc_id", "n_ids", "ids_crc32", "decoded_sha256", "round_trip", "ids"])

    return run


def encoded(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, n_ids, ids_crc32, decoded_sha256, round_trip, ids) for each row."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_run(path), "doc_id long, n_ids long, ids_crc32 long, decoded_sha256 string, round_trip boolean, ids array<int>")


def decoded(rows: DataFrame, path: str) -> DataFrame:
    """(doc_id, text) of rows (doc_id, ids)."""

    def run(batches):
        v = encoder(path).vocabulary
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([v.decode(np.array(x.as_py() or [], np.int64)).decode(errors="replace") for x in b.column(1)])], names=["doc_id", "text"])

    return rows.select(F.col("doc_id").cast("long").alias("doc_id"), "ids").mapInArrow(run, "doc_id long, text string")


def op10_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return encoded(documents(spark, sf_dir, "doc_id", "text"), str(public_tokenizers.path("piece_bpe_32k.model")))
