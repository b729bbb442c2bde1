"""Suffix-array dedup: repeated strings by threshold-bounded interval expansion.

Every start of a `length`-byte string belongs to one anchor: the least hash among the grams inside the string, which depends
on the string alone. Equal strings therefore have equal anchors at equal distances, and only the stretches around anchors
that occur twice can hold a repeat. Stretches with the same anchor meet in one group; their concatenation gets a suffix
array and a Burrows-Wheeler transform, and backward extension of intervals, breadth first, sets common-prefix values in
increasing order up to the threshold. Suffixes whose value with a neighbour was never set share at least `length` bytes.

Equal texts and equal stretches are counted once and carried as a multiplicity. A group of very many different stretches
is dealt out in parts; starts that are single in their text index then meet by the hash of their string all strings of the
other indexes, those that stand there twice or more as well.

Null and empty texts have nothing to remove. Repeated rows are copies of each other. Empty tables give empty results.
"""
from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bytescan import prefix_sums, span_hash
from .common import blocks, documents, release, settle, text_view

LENGTH, GRAM = 400, 64
SALT = 64  # parts of a very common anchor
PART = 2000  # stretches of one anchor that are indexed together
TARGET = 1 << 19  # bytes of stretches from which a text index is closed: its arrays stay in the cache
_POS = np.uint64((1 << 24) - 1)  # places in a piece of a text; pieces overlap
ANCHOR = np.dtype([("h", "<u8"), ("a", "<u4"), ("b", "<u4")])


def _slide_min(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each run of width values."""
    n = len(x) - width + 1
    pad = np.full(-len(x) % width, np.uint64(0xFFFFFFFFFFFFFFFF))
    grid = np.concatenate([x, pad]).reshape(-1, width)
    left = np.minimum.accumulate(grid, axis=1).ravel()
    right = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(right[:n], left[width - 1 : width - 1 + n])


def anchors(data: np.ndarray, offs: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray]:
    """Anchors of all texts, with the first and last start (within the text) that belong to each; and each one's text."""
    n = len(data)
    if n < length:
        return np.zeros(0, ANCHOR), np.zeros(0, np.int64)
    at = np.arange(n - gram + 1)
    h = span_hash(prefix_sums(data), at, at + gram)
    own = np.empty(n - length + 1, np.int64)
    step = int(_POS) + 1 - (length - gram)  # so many starts have grams whose places fit below the hash
    for lo in range(0, len(own), step):
        part = h[lo : lo + step + length - gram]
        low = _slide_min((part & ~_POS) | at[: len(part)].astype(np.uint64), length - gram + 1)
        own[lo : lo + step] = lo + (low & _POS).astype(np.int64)
    size = np.diff(offs)
    valid = np.zeros(n + 1, np.int32)
    long = size >= length
    np.add.at(valid, offs[:-1][long], 1)
    np.add.at(valid, offs[1:][long] - length + 1, -1)
    s = np.flatnonzero(np.cumsum(valid[:n]) > 0)
    if not len(s):
        return np.zeros(0, ANCHOR), np.zeros(0, np.int64)
    o = own[s]
    cut = np.flatnonzero(np.append(True, (o[1:] != o[:-1]) | (s[1:] != s[:-1] + 1)))
    first, last = s[cut], s[np.append(cut[1:], len(s)) - 1]
    doc = np.searchsorted(offs, first, "right") - 1
    out = np.empty(len(cut), ANCHOR)
    out["h"], out["a"], out["b"] = h[o[cut]], first - offs[doc], last - offs[doc]
    return out, doc


# -- one text index -------------------------------------------------------------------------------------------------------

_END = 255  # never a byte of UTF-8; it ends each stretch


def suffix_order(text: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """Suffixes sorted by their first `depth` bytes or more (prefix doubling from eight bytes on), and the marks of the
    places where the first eight bytes change. Both ranks and the place are one number where they fit: a plain sort is faster."""
    n = len(text)
    pad = np.concatenate([text, np.full(8, _END, np.uint8)])
    key = np.ndarray(n, ">u8", pad, strides=(1,)).astype(np.uint64)
    sa = np.argsort(key).astype(np.int32)
    sorted_key = key[sa]
    fresh = np.append(True, sorted_key[1:] != sorted_key[:-1])
    short = fresh.copy()
    rank = np.empty(n, np.int32)
    rank[sa] = np.flatnonzero(fresh).astype(np.int32)[np.cumsum(fresh) - 1]
    h, bits = 8, (n + 1).bit_length()
    rank = np.append(rank + np.int32(1), np.int32(0))  # what lies behind the end comes first
    while h < depth:
        # Only suffixes that still share their rank move.
        single = fresh & np.append(fresh[1:], True)
        at = np.flatnonzero(~single)
        if not len(at):
            break
        part = sa[at]
        pair = rank[part].astype(np.int64) << bits | rank[np.minimum(part + h, n)]
        if 3 * bits < 64:
            pair = pair << bits | np.arange(len(at))
            pair.sort()
            order, pair = pair & ((1 << bits) - 1), pair >> bits
        else:
            order = np.argsort(pair)
            pair = pair[order]
        part = part[order]
        sa[at] = part
        new = np.append(True, pair[1:] != pair[:-1])
        fresh[at] = new
        rank[part] = at[np.flatnonzero(new)[np.cumsum(new) - 1]].astype(np.int32) + np.int32(1)
        h *= 2
    return sa, short


def shared_starts(text: np.ndarray, length: int) -> np.ndarray:
    """True where the `length` bytes from a place on also start elsewhere in text.

    Intervals of the suffix order are extended backwards, breadth first, from those of eight bytes; a boundary that is met
    for the first time in round r has a common prefix of r bytes. Boundaries that no round below `length` met join suffixes
    that share `length` bytes or more.
    """
    n = len(text)
    sa, known = suffix_order(text, length)
    known = np.append(known, True)  # known[i]: the common prefix of places i - 1 and i is below the round's length
    isa = np.empty(n, np.int32)
    isa[sa] = np.arange(n, dtype=np.int32)
    before = isa[np.where(sa > 0, sa - 1, 0)]
    before[sa == 0] = -1
    lead = text[sa]
    lo = np.flatnonzero(known[:-1])
    hi = np.append(lo[1:], n)
    for _ in range(8, length):
        size = hi - lo
        stop = np.cumsum(size)
        at = np.repeat(lo - (stop - size), size) + np.arange(int(stop[-1]) if len(stop) else 0)
        to = before[at]
        src = np.repeat(np.arange(len(lo)), size)
        if (to < 0).any():
            src, to = src[to >= 0], to[to >= 0]
        if not len(to):
            break
        order = np.argsort(to, kind="stable")
        to, src = to[order].astype(np.int64), src[order]
        edge = np.append((to[1:] != to[:-1] + 1) | (src[1:] != src[:-1]) | (lead[to[1:]] != lead[to[:-1]]), True)
        right = np.flatnonzero(edge)
        left = np.append(0, right[:-1] + 1)
        new = ~known[to[right] + 1]
        lo, hi = to[left[new]], to[right[new]] + 1
        known[hi] = True
        if not len(lo):
            break
    tied = ~known
    out = np.zeros(n, bool)
    out[sa] = tied[:-1] | tied[1:]
    return out


def _runs(hit: np.ndarray) -> np.ndarray:
    """(first, last) of each run of True, end to end."""
    edge = np.flatnonzero(np.diff(np.concatenate([[0], hit.astype(np.int8), [0]])))
    edge[1::2] -= 1
    return edge.astype("<u4")


def _index(length: int, part: int, target: int):
    """Streams stretches sorted by (h, part) through text indexes that hold whole parts."""

    def solve(rows: list) -> list:
        size = np.array([len(r[5]) for r in rows])
        text = np.frombuffer(b"".join(r[5] + b"\xff" for r in rows), np.uint8)
        hit = shared_starts(text, length)
        at, out, seen = 0, [], {}
        for (h, _, m1, m2, n, seg), k in zip(rows, size.tolist(), strict=True):
            own = hit[at : at + k - length + 1]
            single = None
            if n > part:  # other indexes may hold the same strings of this anchor
                s = np.arange(len(own))
                w = span_hash(prefix_sums(np.frombuffer(seg, np.uint8)), s, s + length).view("<i8")
                if own.any():
                    seen.setdefault(h, []).append(w[own])
                if not own.all():
                    single = np.concatenate([s[~own].astype("<i8"), w[~own]]).tobytes()
            if own.any() or single is not None:
                out.append((h, m1, m2, _runs(own).tobytes(), single))
            at += k + 1
        for h, ws in seen.items():  # strings that stand here twice or more: one row each, without a start
            w = np.unique(np.concatenate(ws))
            out.append((h, 0, 0, b"", np.concatenate([np.full(len(w), -1, "<i8"), w]).tobytes()))
        return out

    def emit(rows: list) -> pa.RecordBatch:
        cols = list(zip(*rows, strict=True)) or [[]] * 5
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary()]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=["h", "m1", "m2", "runs", "single"])

    def run(batches):
        held, size, last = [], 0, None
        for b in batches:
            for row in zip(*(b.column(i).to_pylist() for i in range(6)), strict=True):
                if size > target and row[:2] != last:
                    yield emit(solve(held))
                    held, size = [], 0
                held.append(row)
                size += len(row[5])
                last = row[:2]
        if held:
            yield emit(solve(held))

    return run


# -- the distributed parts --------------------------------------------------------------------------------------------------


def _anchor_rows(length: int, gram: int):
    def run(batches):
        for b in batches:
            data, offs = text_view(b.column(1))
            raw = data.tobytes()
            n = len(offs) - 1
            found: list[bytes] = [b""] * n
            for lo, hi in blocks(offs):
                a, doc = anchors(data[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo], length, gram)
                cut = np.searchsorted(doc, np.arange(hi - lo + 1))
                for i in range(hi - lo):
                    found[lo + i] = a[cut[i] : cut[i + 1]].tobytes()
            sha = [hashlib.sha256(raw[offs[i] : offs[i + 1]]).digest() for i in range(n)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([s[:16] for s in sha], pa.binary()), pa.array([s.hex() for s in sha]), pa.array(np.diff(offs)), pa.array(found, pa.binary())], names=["doc_id", "tid", "sha", "n", "anchors"])

    return run


def _spread_anchors(batches):
    for b in batches:
        raw = [x.as_py() for x in b.column(1)]
        a = np.frombuffer(b"".join(raw), ANCHOR)
        back = np.repeat(np.arange(len(raw)), [len(x) // ANCHOR.itemsize for x in raw])
        for lo in range(0, max(1, len(a)), 1 << 18):
            part, own = a[lo : lo + (1 << 18)], back[lo : lo + (1 << 18)]
            at = pa.array(own)
            yield pa.RecordBatch.from_arrays([b.column(0).take(at), b.column(2).take(at), pa.array(part["h"].astype(np.int64)), pa.array(part["a"].astype(np.int64)), pa.array(part["b"].astype(np.int64))], names=["tid", "c", "h", "a", "b"])


def _stretches(raw: bytes, hits: list, length: int):
    """(h, a, b, m1, m2, bytes) of each anchor's stretch."""
    for x in hits:
        seg = raw[x["a"] : x["b"] + length]
        m = hashlib.md5(seg, usedforsecurity=False).digest()
        yield x["h"], x["a"], x["b"], int.from_bytes(m[:8], "little", signed=True), int.from_bytes(m[8:], "little", signed=True), seg


def _keys(length: int):
    def run(batches):
        for b in batches:
            rows = []
            for tid, c, text, hits in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), b.column(3), strict=True):
                rows += [(tid, min(c, 2), h, a, z, m1, m2) for h, a, z, m1, m2, _ in _stretches(text.as_py().encode(), hits.as_py(), length)]
            cols = list(zip(*rows, strict=True)) or [[]] * 7
            kinds = [pa.binary(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=["tid", "c", "h", "a", "b", "m1", "m2"])

    return run


def _bodies(length: int, part: int):
    def run(batches):
        for b in batches:
            rows = []
            for text, hits, want in zip(b.column(0), b.column(1), b.column(2), strict=True):
                todo = {(w["h"], w["m1"], w["m2"]): w["nd"] for w in want.as_py()}
                for h, _, _, m1, m2, seg in _stretches(text.as_py().encode(), hits.as_py(), length):
                    nd = todo.pop((h, m1, m2), None)
                    if nd is not None:
                        rows.append((h, (m1 & 0x7FFFFFFF) % -(-nd // part), m1, m2, nd, seg))
            cols = list(zip(*rows, strict=True)) or [[]] * 6
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=["h", "part", "m1", "m2", "nd", "seg"])

    return run


def _single_rows(batches):
    for b in batches:
        for h, m1, m2, s in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
            v = np.frombuffer(s, "<i8")
            k = len(v) // 2
            yield pa.RecordBatch.from_arrays([pa.array(np.full(k, h)), pa.array(np.full(k, m1)), pa.array(np.full(k, m2)), pa.array(v[:k]), pa.array(v[k:])], names=["h", "m1", "m2", "s", "w"])


def covered(n: int, spans: list, length: int) -> np.ndarray:
    """Bytes of a text of n bytes under repeated strings; spans: {a, b, runs, more}: runs of
    starts or single starts; the whole stretch without either."""
    edge = np.zeros(n + 1, np.int32)
    for x in spans:
        r = [(0, x["b"] - x["a"])] if x["runs"] is None else np.frombuffer(x["runs"], "<u4").reshape(-1, 2).tolist()
        if x["more"] is not None:
            r = [(s, s) for s in x["more"]]
        for s, e in r:
            edge[x["a"] + s] += 1
            edge[min(n, x["a"] + e + length)] -= 1
    return np.cumsum(edge[:n]) > 0


def _cleaner(length: int, keep_text: bool):
    def run(batches):
        for b in batches:
            rows = []
            for tid, text, spans in zip(b.column(0).to_pylist(), b.column(1), b.column(2), strict=True):
                raw = np.frombuffer(text.as_py().encode(), np.uint8)
                hit = covered(len(raw), spans.as_py(), length)
                left = raw[~hit].tobytes()
                rows.append((tid, int(hit.sum()), len(_runs(hit)) // 2, hashlib.sha256(left).hexdigest(), left.decode(errors="ignore") if keep_text else None))
            cols = list(zip(*rows, strict=True)) or [[]] * 5
            kinds = [pa.binary(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=["tid", "n_removed", "n_spans", "kept_sha256", "kept"])

    return run


_NONE = hashlib.sha256(b"").hexdigest()


def repeat_tables(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, part: int = PART, keep_text: bool = False, target: int = TARGET) -> tuple[DataFrame, DataFrame]:
    """Two tables: each row's doc_id, text key (tid), digest and size; and per text key with something to remove: n_removed, n_spans,
    kept_sha256 and, with keep_text, what is left (kept; bytes of a character that was cut through are left out)."""
    gram = min(gram, length)
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    marks = settle(src.mapInArrow(_anchor_rows(length, gram), "doc_id long, tid binary, sha string, n long, anchors binary"), "anchors")
    texts = marks.where(F.col("n") >= length).groupBy("tid").agg(F.min("doc_id").alias("rep"), F.count("*").alias("c"), F.max("anchors").alias("anchors"))
    spread = texts.select("tid", "anchors", "c").mapInArrow(_spread_anchors, "tid binary, c long, h long, a long, b long")
    twice = settle(spread.groupBy("h").agg(F.count("*").alias("k")).where("k > 1"), "twice")
    # Anchors that hold more than a 4096th of the repeated places are fewer than 4096; theirs are dealt by text as well.
    hot = F.broadcast(twice.where(F.col("k") > (twice.agg(F.sum("k")).first()[0] or 0) // 4096).select("h", F.lit(SALT).alias("z")))
    deal = lambda df, z: df.join(hot, "h", "left").withColumn("z", z)
    dealt = deal(spread, F.when(F.col("z").isNull(), 0).otherwise(F.pmod(F.xxhash64("tid"), F.lit(SALT)).cast("int")))
    copies = deal(twice.select("h"), F.explode(F.sequence(F.lit(0), F.coalesce("z", F.lit(1)) - 1)))
    own = dealt.join(copies, ["h", "z"]).groupBy("tid").agg(F.max("c").alias("c"), F.sort_array(F.collect_list(F.struct("a", "b", "h"))).alias("hits"))
    where = own.join(texts.select("tid", "rep"), "tid").hint("shuffle_hash")
    # A representative is found by its id and proved by its digest, so repeated or null ids do no harm.
    held = settle(src.join(where, src["doc_id"].eqNullSafe(where["rep"])).where(F.expr("substring(unhex(sha2(text, 256)), 1, 16) = tid")).select("tid", "c", "text", "hits"), "held")
    keys = held.mapInArrow(_keys(length), "tid binary, c long, h long, a long, b long, m1 long, m2 long")
    kinds = settle(keys.groupBy("h", "m1", "m2").agg(F.sum("c").alias("c"), F.min("tid").alias("tid")), "kinds")
    groups = kinds.groupBy("h").agg(F.count("*").alias("nd"), F.sum((F.col("c") == 1).cast("int")).alias("ns")).where("nd > 1 and ns > 0").select("h", "nd")
    want = kinds.join(groups, "h").groupBy("tid").agg(F.collect_list(F.struct("h", "m1", "m2", "nd")).alias("want"))
    bodies = held.select("tid", "text", "hits").join(want.hint("shuffle_hash"), "tid").select("text", "hits", "want").mapInArrow(_bodies(length, part), "h long, part long, m1 long, m2 long, nd long, seg binary")
    found = settle(bodies.repartition("h", "part").sortWithinPartitions("h", "part").mapInArrow(_index(length, part, target), "h long, m1 long, m2 long, runs binary, single binary"), "found")
    single = found.where("single is not null").select("h", "m1", "m2", "single").mapInArrow(_single_rows, "h long, m1 long, m2 long, s long, w long")
    # Every string of a text index has one row here, with its start where it is single; they are counted over the indexes.
    met = single.groupBy("h", "w").agg(F.count("*").alias("k")).where("k > 1").select("h", "w")
    none, nil = F.lit(None).cast("binary").alias("runs"), F.lit(None).cast("array<long>").alias("more")
    late = single.where("s >= 0").join(met, ["h", "w"]).groupBy("h", "m1", "m2").agg(F.collect_list("s").alias("more")).select("h", "m1", "m2", none, "more")
    full = kinds.where("c > 1").select("h", "m1", "m2", none, nil)
    partial = found.where(F.octet_length("runs") > 0).select("h", "m1", "m2", "runs", nil).unionByName(late)
    done = full.unionByName(partial.join(full.select("h", "m1", "m2"), ["h", "m1", "m2"], "left_anti"))
    spans = keys.select("tid", "h", "m1", "m2", "a", "b").join(done, ["h", "m1", "m2"]).groupBy("tid").agg(F.collect_list(F.struct("a", "b", "runs", "more")).alias("spans"))
    cleaned = held.where("c = 1").select("tid", "text").join(spans.hint("shuffle_hash"), "tid").mapInArrow(_cleaner(length, keep_text), "tid binary, n_removed long, n_spans long, kept_sha256 string, kept string")
    copies = marks.where(F.col("n") >= length).groupBy("tid").agg(F.count("*").alias("c"), F.max("n").alias("n_removed")).where("c > 1").select("tid", "n_removed", F.lit(1).cast("long").alias("n_spans"), F.lit(_NONE).alias("kept_sha256"), F.lit("").alias("kept"))
    news = settle(cleaned.unionByName(copies), "cleaned")
    for t in (twice, held, kinds, found):
        release(t)
    return marks, news


def repeats(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, part: int = PART, target: int = TARGET) -> DataFrame:
    """One row for each row of docs (doc_id, text): doc_id, n_bytes, n_removed, n_spans, kept_sha256."""
    marks, news = repeat_tables(docs, length, gram, part, target=target)
    zero = F.lit(0).cast("long")
    out = marks.select("doc_id", "tid", "sha", "n").join(news, "tid", "left")
    return out.select("doc_id", F.col("n").alias("n_bytes"), F.coalesce("n_removed", zero).alias("n_removed"), F.coalesce("n_spans", zero).alias("n_spans"), F.coalesce("kept_sha256", "sha").alias("kept_sha256"))


def without_repeats(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """docs, all columns, with repeated strings taken out of text (n_chars follows where there is such a column)."""
    _, news = repeat_tables(docs, length, keep_text=True)
    key = F.expr("substring(unhex(sha2(coalesce(cast(text as string), ''), 256)), 1, 16)")
    rows = docs.select(F.struct(*docs.columns).alias("r"), key.alias("k")).join(news.select(F.col("tid").alias("k"), "kept"), "k", "left")
    new = {"text": F.coalesce("kept", F.col("r.text").cast("string")).cast(docs.schema["text"].dataType)}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(F.col("kept").isNull(), F.col("r.n_chars")).otherwise(F.char_length("kept").cast(docs.schema["n_chars"].dataType))
    return rows.select(*(new.get(c, F.col("r")[c]).alias(c) for c in docs.columns))


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats(documents(spark, sf_dir, "doc_id", "text"))
