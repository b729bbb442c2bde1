"""Binary vector files: records of a 32-bit dimension and that many numbers (fvecs, bvecs, ivecs)."""
from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

KINDS = {"fvecs": "<f4", "ivecs": "<i4", "bvecs": "u1"}


def parsed(files: DataFrame, kind: str = "fvecs") -> DataFrame:
    """(vec_id, embedding) of file contents (content, h): ids count from h."""
    item = np.dtype(KINDS[kind])

    def run(batches):
        for b in batches:
            for blob, h in zip(b.column(0), b.column(1).to_pylist(), strict=True):
                raw = blob.as_py()
                if not raw:
                    continue
                d = int(np.frombuffer(raw[:4], "<i4")[0])
                rows = np.frombuffer(raw, np.uint8).reshape(-1, 4 + d * item.itemsize)[:, 4:]
                x = np.ascontiguousarray(rows).view(item).astype(np.float32)
                for lo in range(0, len(x), 10_000):
                    part = x[lo : lo + 10_000]
                    flat = pa.ListArray.from_arrays(pa.array(np.arange(len(part) + 1, dtype=np.int32) * d), pa.array(part.ravel()))
                    yield pa.RecordBatch.from_arrays([pa.array(h + np.arange(lo, lo + len(part))), flat], names=["vec_id", "embedding"])

    return files.select("content", "h").mapInArrow(run, "vec_id long, embedding array<float>")


def read_vecs(spark: SparkSession, path: str, kind: str = "fvecs") -> DataFrame:
    """(vec_id, embedding): ids count within a file; several files get disjoint ranges by the hash of their name."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", f"*.{kind}").load(path)
    one = files.count() == 1
    base = F.lit(0).cast("long") if one else F.shiftleft(F.xxhash64("path").bitwiseAND(F.lit(0x3FFFFF)), 40)
    return parsed(files.select("content", base.alias("h")), kind)


def to_fvecs(x: np.ndarray) -> bytes:
    """The file of a matrix."""
    n, d = x.shape
    out = np.empty((n, 4 + 4 * d), np.uint8)
    out[:, :4] = np.frombuffer(np.int32(d).tobytes(), np.uint8)
    out[:, 4:] = np.ascontiguousarray(x, "<f4").view(np.uint8).reshape(n, -1)
    return out.tobytes()
