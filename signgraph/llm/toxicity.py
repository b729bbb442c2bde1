"""Toxicity: multiple-instance learning over sentences.

A text is a bag of sentences (ended by . ! ? or a line end). Each sentence has a logistic score over its hashed lower-case
words and their stems; the document's score is their noisy-or, 1 - prod(1 - s). Only document labels are given in training; the gradient
reaches sentences through the noisy-or. `locate` then gives the sentences that offend.

Fitted on the driver from at most `sample` labelled rows (half of each label at most). A null or empty text has no
sentence and scores the noisy-or of one empty sentence; repeated rows get equal scores; without both labels the score is
the share of label 1 (0 if there are none). Extra columns are ignored.
"""
from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bytescan import LETTER, LOWER, STOP, prefix_sums, runs, span_hash
from .common import blocks, documents, text_view
from .quality import held_out, sample_rows

BITS = 20
STEMS = (4, 5)


def words(data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash buckets and starts of features: each word whole, and its first four and five bytes as stems."""
    low = LOWER[data]
    s, e = runs(LETTER[data], offs)
    sums, cut = prefix_sums(low), np.uint64(64 - BITS)
    h = [span_hash(sums, s, e) >> cut]
    starts = [s]
    for n in STEMS:
        at = s[e - s > n]
        with np.errstate(over="ignore"):
            h.append(span_hash(sums, at, at + n) * np.uint64(2 * n + 1) >> cut)
        starts.append(at)
    h, s = np.concatenate(h).astype(np.int64), np.concatenate(starts)
    order = np.argsort(s, kind="stable")
    return h[order], s[order]


def sentences(data: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """Starts of sentences, at least one for each text that has a byte."""
    start = np.zeros(len(data) + 1, bool)
    start[1:] = STOP[data] if len(data) else False
    start[offs] = True
    return np.flatnonzero(start[: len(data)])


def _bags(data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Words' buckets, words' sentences (numbered through), sentences' documents, sentences' starts."""
    h, s = words(data, offs)
    at = sentences(data, offs)
    return h, np.searchsorted(at, s, "right") - 1, np.searchsorted(offs, at, "right") - 1, at


def fit(docs: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray, lift: float = 6.0, steps: int = 200) -> dict:
    """Weighs the buckets that documents of label 1 hold `lift` times as often as the others, in four documents or more."""
    held = [np.unique(b) for b, _ in docs]
    pos = np.bincount(np.concatenate([h for h, k in zip(held, y, strict=True) if k]), minlength=1 << BITS)
    neg = np.bincount(np.concatenate([h for h, k in zip(held, y, strict=True) if not k]), minlength=1 << BITS)
    n1, n0 = y.sum(), len(y) - y.sum()
    return _fit(docs, y, 2e-6, (pos >= max(4, 0.004 * n1)) & (pos / n1 >= lift * (neg + 1) / n0), steps)


def _fit(docs: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray, thrift: float, allowed: np.ndarray, steps: int, rate: float = 0.15) -> dict:
    """docs: buckets and sentence numbers of each document. Proximal steps with an L1 price of `thrift`,
    which keeps chance words at zero; only `allowed` buckets can leave it."""
    w, bias = np.zeros(1 << BITS), -8.0
    count = np.array([s[-1] + 1 if len(s) else 1 for _, s in docs])
    base = np.concatenate([[0], np.cumsum(count)])
    tok = np.concatenate([b for b, _ in docs])
    sent = np.concatenate([s + base[i] for i, (_, s) in enumerate(docs)])
    live = allowed[tok]
    tok, sent = tok[live], sent[live]
    # One feature counts once in a sentence.
    pair = np.unique(sent.astype(np.int64) << BITS | tok)
    sent, tok = pair >> BITS, pair & (1 << BITS) - 1
    used, tok = np.unique(tok, return_inverse=True)
    wu = np.zeros(len(used))
    doc = np.repeat(np.arange(len(docs)), count)
    share = float(np.clip(y.mean(), 1e-3, 1 - 1e-3))
    cost = np.where(y > 0, 0.5 / share, 0.5 / (1 - share)) / len(y)
    # Accelerated proximal gradient; the step of each coordinate follows the share of documents that hold it.
    scale = np.sqrt(np.bincount(tok, cost[doc[sent]], len(used)) + 1e-3)
    past, ahead, bias_ahead, bias_past = wu, wu, bias, bias
    for t in range(1, steps + 1):
        z = np.bincount(sent, ahead[tok], base[-1]) + bias_ahead
        p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        none = np.bincount(doc, np.log1p(-np.minimum(p, 1 - 1e-9)), len(docs))
        some = np.maximum(-np.expm1(none), 1e-6)
        pull = np.where(y > 0, -(1 - some) / some, 1.0) * cost
        g = pull[doc] * p
        step = rate * 20 / scale
        wu = ahead - step * np.bincount(tok, g[sent], len(used))
        wu = np.clip(wu - step * thrift, 0, 12)
        bias = float(np.clip(bias_ahead - rate * 4 * g.sum(), -12, -6))
        k = (t - 1) / (t + 2)
        ahead, bias_ahead = wu + k * (wu - past), bias + k * (bias - bias_past)
        past, bias_past = wu, bias
    w[used] = wu
    return {"w": w.astype(np.float32), "b": float(bias)}


def _features(batches):
    for b in batches:
        data, offs = text_view(b.column(1))
        h, s, d, _ = _bags(data, offs)
        first = np.searchsorted(d, np.arange(len(offs) - 1))
        cut = np.searchsorted(s, np.append(first, len(d)))
        hs, ss = [], []
        for i in range(len(offs) - 1):
            hs.append(h[cut[i] : cut[i + 1]].astype(np.int32).tobytes())
            ss.append((s[cut[i] : cut[i + 1]] - first[i]).astype(np.int32).tobytes())
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array(hs, pa.binary()), pa.array(ss, pa.binary()), b.column(2)], names=["doc_id", "h", "s", "y"])


def train(docs: DataFrame, labels: DataFrame, sample: int = 5000, skip_mod: int = 5, skip_rest: int = 0, **fitting) -> dict:
    rows = sample_rows(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), labels, "toxic", skip_mod, skip_rest, sample)
    got = sorted(rows.mapInArrow(_features, "doc_id long, h binary, s binary, y int").collect())
    y = np.array([r["y"] for r in got], np.float64)
    if len(y) < 8 or y.min() == y.max():
        return {"const": float(y.mean()) if len(y) else 0.0}
    return fit([(np.frombuffer(r["h"], np.int32).astype(np.int64), np.frombuffer(r["s"], np.int32).astype(np.int64)) for r in got], y, **fitting)


def sentence_scores(w: dict, data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Score, document and start of each sentence."""
    h, s, d, at = _bags(data, offs)
    x = w["w"][h]
    hit = np.flatnonzero(x)
    pair = np.unique(s[hit] << BITS | h[hit])
    z = np.bincount(pair >> BITS, w["w"][pair & (1 << BITS) - 1], len(at)) + w["b"]
    return 1 / (1 + np.exp(-np.clip(z, -30, 30))), d, at


_SCORED = "doc_id long, score double, n_offending int, offending_starts array<int>, offending_lengths array<int>"


def _scorer(w: dict):
    def run(batches):
        for b in batches:
            data, offs = text_view(b.column(1))
            n = len(offs) - 1
            out, bad, starts, lengths = np.zeros(n), np.zeros(n, np.int32), [], []
            for lo, hi in blocks(offs):
                if "const" in w:
                    out[lo:hi] = w["const"]
                    continue
                part, po = data[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo]
                p, d, at = sentence_scores(w, part, po)
                none = np.bincount(d, np.log1p(-np.minimum(p, 1 - 1e-12)), hi - lo)
                none = np.where(np.bincount(d, minlength=hi - lo) > 0, none, -np.log1p(np.exp(w["b"])))
                out[lo:hi] = -np.expm1(none)
                k = np.flatnonzero(p >= 0.5)
                bad[lo:hi] = np.bincount(d[k], minlength=hi - lo)
                starts.append(at[k] - po[d[k]])
                lengths.append(np.minimum(np.append(at[1:], len(part))[k], po[d[k] + 1]) - at[k])
            edge = pa.array(np.concatenate([[0], np.cumsum(bad)]).astype(np.int32))
            where = [pa.ListArray.from_arrays(edge, pa.array(np.concatenate(v).astype(np.int32) if v else np.zeros(0, np.int32))) for v in (starts, lengths)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.float64()), pa.array(bad, pa.int32()), *where], names=[c.split()[0] for c in _SCORED.split(", ")])

    return run


def scored(docs: DataFrame, w: dict) -> DataFrame:
    """(doc_id, score, n_offending, offending_starts, offending_lengths) for each row: sentences of a score of 0.5 or more, in bytes of
    the UTF-8 text."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_scorer(w), _SCORED)


def locate(docs: DataFrame, w: dict, least: float = 0.5) -> DataFrame:
    """(doc_id, start, length, score, sentence): sentences that reach `least`, in bytes of the UTF-8 text."""

    def run(batches):
        for b in batches:
            data, offs = text_view(b.column(1))
            ids = b.column(0).to_pylist()
            for lo, hi in blocks(offs):
                part, po = data[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo]
                p, d, at = (np.zeros(0), np.zeros(0, int), np.zeros(0, int)) if "const" in w else sentence_scores(w, part, po)
                end = np.append(at[1:], len(part))
                k = np.flatnonzero(p >= least)
                rows = [(ids[lo + d[i]], int(at[i] - po[d[i]]), int(end[i] - at[i]), float(p[i]), part[at[i] : end[i]].tobytes().decode(errors="replace")) for i in k]
                cols = list(zip(*rows, strict=True)) or [[]] * 5
                kinds = [pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.string()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=["doc_id", "start", "length", "score", "sentence"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, start long, length long, score double, sentence string")


def op6_toxicity_mil(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir, "doc_id", "text")
    w = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return scored(docs, w).select("doc_id", held_out(5, 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "n_offending", "offending_starts", "offending_lengths")
