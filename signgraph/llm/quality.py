"""Quality: a convolutional network on bytes, in numpy.

A text is read whole as UTF-8. Bytes are embedded, learned filters of eight bytes slide over it by four, and overlapping
chunks of 512 bytes (stride 256) pool them by maximum and mean; a hidden layer scores each chunk, chunk scores are pooled
by maximum and mean over the document, and a last layer combines them into one probability.

The network is fitted on the driver from a bounded sample of labelled rows, each with all chunks of its whole text: at most
`sample` rows, half of each label at most, taken by the hash of the id until their texts make `volume` bytes; a text of more than
`longest` bytes is no sample row, as its activations would not fit. Scoring reads whole texts in Arrow batches and
depends on the text alone. A null text is an empty one and is scored like it; repeated rows get equal scores; without
labels of both kinds the score is the share of label 1 (0.5 if there are none). Extra columns are ignored.
"""
from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import blocks, documents, text_view

GROUP, HALF = 4, 256
EMBED, FILTERS, HIDDEN = 8, 24, 16
STEPS = HALF // GROUP


def start_weights(seed: int) -> dict[str, np.ndarray]:
    r = np.random.default_rng(seed)
    w = {
        "e": r.normal(0, 0.5, (256, EMBED)), "a": r.normal(0, 0.18, (GROUP * EMBED, 2 * FILTERS)), "ab": np.zeros(FILTERS),
        "h": r.normal(0, 0.2, (2 * FILTERS, HIDDEN)), "hb": np.zeros(HIDDEN), "o": r.normal(0, 0.2, 2 * HIDDEN), "ob": np.zeros(1),
    }
    return {k: v.astype(np.float32) for k, v in w.items()}


def _forward(w: dict, x: np.ndarray, real: np.ndarray, first: np.ndarray) -> dict:
    """x: bytes of whole halves end to end; real: groups with a byte of the text, by half; first: index of the first half of each document."""
    halves, docs = len(real), len(first)
    count = np.diff(np.append(first, halves))
    last = first + count - 1
    e = w["e"][x].reshape(-1, GROUP * EMBED)
    c = e @ w["a"]
    z = c[:, :FILTERS] + w["ab"]
    z[:-1] += c[1:, FILTERS:]
    ends = (last + 1) * STEPS - 1  # the next group is another document's
    z[ends] = c[ends, :FILTERS] + w["ab"]
    act = np.maximum(z, 0).reshape(halves, STEPS, FILTERS)
    act *= (np.arange(STEPS)[None, :] < real[:, None])[:, :, None]
    top, total = act.max(1), act.sum(1)
    # A chunk is a half and the one after it in the same document.
    nxt = np.minimum(np.arange(halves) + 1, np.repeat(last, count))
    alone = nxt == np.arange(halves)
    n = real + np.where(alone, 0, real[nxt])
    cmax = np.maximum(top, top[nxt])
    cmean = (total + np.where(alone[:, None], 0, total[nxt])) / np.maximum(n, 1)[:, None]
    keep = ~alone | (np.repeat(count, count) == 1)  # the last half is inside the chunk before it
    v = np.concatenate([cmax, cmean * 4], 1)
    hz = v @ w["h"] + w["hb"]
    h = np.tanh(hz)
    masked = np.where(keep[:, None], h, -9).astype(np.float32)
    hmax = np.maximum.reduceat(masked, first)
    chunks = np.add.reduceat(keep.astype(np.float32), first)
    hmean = np.add.reduceat(np.where(keep[:, None], h, 0), first) / chunks[:, None]
    logit = np.concatenate([hmax, hmean], 1) @ w["o"] + w["ob"][0]
    return locals()


def _lay_out(texts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    size = np.array([len(t) for t in texts], np.int64)
    halves = np.maximum(1, -(-size // HALF))
    first = np.concatenate([[0], np.cumsum(halves)[:-1]])
    x = np.zeros(int(halves.sum()) * HALF, np.uint8)
    for t, at in zip(texts, first, strict=True):
        x[at * HALF : at * HALF + len(t)] = t
    at = np.arange(int(halves.sum())) - np.repeat(first, halves)
    real = np.clip(-(-(np.repeat(size, halves) - at * HALF) // GROUP), 0, STEPS)
    return x, real, first


def logits(w: dict, texts: list[np.ndarray]) -> np.ndarray:
    """Raw scores of whole texts."""
    return _forward(w, *_lay_out(texts))["logit"] if texts else np.zeros(0, np.float32)


def _gradient(w: dict, texts: list[np.ndarray], y: np.ndarray, weight: np.ndarray) -> tuple[dict, float]:
    s = _forward(w, *_lay_out(texts))
    p = 1 / (1 + np.exp(-s["logit"]))
    loss = float(-(weight * np.where(y > 0, np.log(p + 1e-7), np.log(1 - p + 1e-7))).mean())
    d = ((p - y) * weight / len(y)).astype(np.float32)
    g = {"ob": np.array([d.sum()], np.float32), "o": np.concatenate([s["hmax"], s["hmean"]], 1).T @ d}
    count, first, keep, h, nxt = s["count"], s["first"], s["keep"], s["h"], s["nxt"]
    doc = np.repeat(np.arange(len(first)), count)
    dh = np.where(keep[:, None], d[doc, None] * w["o"][HIDDEN:] / s["chunks"][doc, None], 0)
    hit = (s["masked"] == s["hmax"][doc]) & keep[:, None]
    share = np.add.reduceat(hit.astype(np.float32), first)
    dh = dh + hit * (d[doc, None] * w["o"][:HIDDEN]) / share[doc]
    dz = (dh * (1 - h * h)).astype(np.float32)
    g["hb"], g["h"] = dz.sum(0), s["v"].T @ dz
    dv = dz @ w["h"].T
    dmax, dmean = dv[:, :FILTERS], dv[:, FILTERS:] * 4 / np.maximum(s["n"], 1)[:, None]
    top, own = s["top"], s["top"] >= s["top"][nxt]
    dtop = np.where(own, dmax, 0)
    np.add.at(dtop, nxt, np.where(own, 0, dmax))
    dtotal = dmean.copy()
    np.add.at(dtotal, nxt[~s["alone"]], dmean[~s["alone"]])
    act = s["act"]
    at_top = act.argmax(1)
    dact = np.repeat(dtotal[:, None, :], STEPS, 1)
    i, k = np.indices(at_top.shape)
    dact[i, at_top, k] += dtop
    dact = (dact * (act > 0)).reshape(-1, FILTERS).astype(np.float32)
    g["ab"] = dact.sum(0)
    dc = np.zeros((len(dact), 2 * FILTERS), np.float32)
    dc[:, :FILTERS] = dact
    after = dact[:-1].copy()
    ends = s["ends"]
    after[ends[ends < len(after)]] = 0
    dc[1:, FILTERS:] = after
    g["a"] = s["e"].T @ dc
    de = (dc @ w["a"].T).reshape(-1, EMBED)
    x = s["x"]
    g["e"] = np.stack([np.bincount(x, de[:, k], 256) for k in range(EMBED)], 1).astype(np.float32)
    return g, loss


def fit(texts: list[np.ndarray], y: np.ndarray, epochs: int = 8, seed: int = 7, rate: float = 0.006, batch: int = 48) -> dict:
    """Adam on a class-balanced log loss."""
    w, r = start_weights(seed), np.random.default_rng(seed)
    share = float(np.clip(y.mean(), 1e-3, 1 - 1e-3))
    weight = np.where(y > 0, 0.5 / share, 0.5 / (1 - share)).astype(np.float32)
    m, v, t = {k: 0 * x for k, x in w.items()}, {k: 0 * x for k, x in w.items()}, 0
    size = np.array([len(t) for t in texts])
    plans = []
    for _ in range(epochs):  # batches of `batch` texts, or fewer where they are long
        part: list[int] = []
        for i in r.permutation(len(texts)).tolist():
            if part and (len(part) == batch or size[part].sum() + size[i] > LONGEST):
                plans.append(part)
                part = []
            part.append(i)
        plans.append(part)
    steps = len(plans)
    for part in plans:
        g, _ = _gradient(w, [texts[i] for i in part], y[part], weight[part])
        norm = np.sqrt(sum(float((x * x).sum()) for x in g.values()))
        t += 1
        step = rate * 0.5 * (1 + np.cos(np.pi * t / steps))
        for k in w:
            gk = g[k] * min(1.0, 2 / (norm + 1e-9))
            m[k] = 0.9 * m[k] + 0.1 * gk
            v[k] = 0.999 * v[k] + 0.001 * gk * gk
            w[k] = (w[k] - step * (m[k] / (1 - 0.9**t)) / (np.sqrt(v[k] / (1 - 0.999**t)) + 1e-7)).astype(np.float32)
    return w


def sample_rows(docs: DataFrame, labels: DataFrame, label: str, skip_mod: int, skip_rest: int, sample: int) -> DataFrame:
    """(text, y) of at most `sample` labelled rows outside the held-out fold: half of each label, by the hash of the id."""
    rest = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(skip_mod))
    y = F.col(label).cast("int")
    base = labels.where(F.col("doc_id").isNotNull() & y.isin(0, 1) & (rest != skip_rest)).groupBy("doc_id").agg(F.max(y).alias("y"))
    key = [F.xxhash64(F.col("doc_id").cast("string")), F.col("doc_id")]
    pick = base.where("y = 1").orderBy(*key).limit(sample // 2).union(base.where("y = 0").orderBy(*key).limit(sample // 2))
    # At most `sample` ids: their bound is the parameter itself, so a broadcast is safe.
    return docs.select("doc_id", F.coalesce(F.col("text"), F.lit("")).alias("text")).join(F.broadcast(pick), "doc_id").select("doc_id", "text", "y")


#: Bytes of one text, and of one batch of texts, that the fit holds.
LONGEST = 1 << 20


def train(docs: DataFrame, labels: DataFrame, sample: int = 3000, volume: int = 48 << 20, longest: int = LONGEST, skip_mod: int = 4, skip_rest: int = 2, **fitting) -> dict:
    rows = sample_rows(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), labels, "quality", skip_mod, skip_rest, sample)
    size = rows.select("doc_id", F.octet_length("text").alias("n")).where(F.col("n") <= longest).orderBy(F.xxhash64("doc_id"), "doc_id").collect()
    total, ids = 0, []
    for r in size:  # of at most `sample` rows
        total += r["n"]
        if total > volume:
            break
        ids.append(r["doc_id"])
    got = sorted(((r["doc_id"], bytes(r["t"]), r["y"]) for r in rows.where((F.octet_length("text") <= longest) & F.col("doc_id").isin(ids)).select("doc_id", F.col("text").cast("binary").alias("t"), "y").collect())) if ids else []
    y = np.array([r[2] for r in got], np.float32)
    if len(y) < 8 or y.min() == y.max():
        return {"const": float(y.mean()) if len(y) else 0.5}
    w = fit([np.frombuffer(r[1], np.uint8) for r in got], y, **fitting)
    # The fit saw both labels equally often; the last bias moves scores to the odds of the labels themselves.
    fold = labels.where(F.col("doc_id").isNotNull() & F.col("quality").isin(0, 1) & ~held_out(skip_mod, skip_rest))
    share = float(np.clip(fold.agg(F.avg(F.col("quality").cast("double"))).first()[0], 0.02, 0.98))
    w["ob"] = (w["ob"] + np.log(share / (1 - share))).astype(np.float32)
    return w


def score_texts(w: dict, texts: list[np.ndarray]) -> np.ndarray:
    if "const" in w:
        return np.full(len(texts), w["const"])
    return 1 / (1 + np.exp(-np.clip(logits(w, texts).astype(np.float64), -30, 30)))


PIECE = 1 << 20


def _pooled(w: dict, text: np.ndarray) -> float:
    """The raw score of a text of any length, chunk by chunk: pieces carry the two halves behind them, so that their chunks and
    filters see what they see in the whole text."""
    top, total, n = None, 0.0, 0
    for at in range(0, len(text), PIECE):
        s = _forward(w, *_lay_out([text[at : at + PIECE + 2 * HALF]]))
        last = len(text) - at - PIECE <= HALF  # no chunk starts behind this piece
        h = s["h"][s["keep"]][: None if last else PIECE // HALF].astype(np.float64)
        top = h.max(0) if top is None else np.maximum(top, h.max(0))
        total, n = total + h.sum(0), n + len(h)
        if last:
            break
    return float(np.concatenate([top, total / n]) @ w["o"] + w["ob"][0])


def _scorer(w: dict):
    def run(batches):
        for b in batches:
            data, offs = text_view(b.column(1))
            out = np.empty(len(offs) - 1)
            for lo, hi in blocks(offs, 1 << 16):
                if offs[hi] - offs[lo] > PIECE and "const" not in w:
                    out[lo] = 1 / (1 + np.exp(-np.clip(_pooled(w, data[offs[lo] : offs[hi]]), -30, 30)))
                else:
                    out[lo:hi] = score_texts(w, [data[offs[i] : offs[i + 1]] for i in range(lo, hi)])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.float64())], names=["doc_id", "score"])

    return run


def scored(docs: DataFrame, w: dict) -> DataFrame:
    """(doc_id, score) for each row."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_scorer(w), "doc_id long, score double")


def held_out(mod: int, rest: int):
    return F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(mod)) == rest


def keep_good(docs: DataFrame, w: dict, threshold: float = 0.7) -> DataFrame:
    """Rows of docs, all columns, whose score reaches the threshold."""
    keep = threshold
    names = [f.name for f in docs.schema.fields]
    at = names.index("text")

    def run(batches):
        for b in batches:
            data, offs = text_view(b.column(at))
            ok = np.zeros(len(offs) - 1, bool)
            for lo, hi in blocks(offs, 1 << 16):
                if offs[hi] - offs[lo] > PIECE and "const" not in w:
                    ok[lo] = 1 / (1 + np.exp(-np.clip(_pooled(w, data[offs[lo] : offs[hi]]), -30, 30))) >= keep
                else:
                    ok[lo:hi] = score_texts(w, [data[offs[i] : offs[i + 1]] for i in range(lo, hi)]) >= keep
            yield b.filter(pa.array(ok))

    return docs.mapInArrow(run, docs.schema)


def op4_byte_cnn(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir, "doc_id", "text")
    w = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    out = scored(docs, w)
    return out.select("doc_id", held_out(4, 2).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))
