"""From a block or window held as a DataFrame to one vector: tall-skinny QR by tasks, a small problem on the driver."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import smalldense
from .block import columns, width_of

FAN = 64  # triangles that meet in one task of the combining tree


def _stack(parts: list[bytes], m: int) -> np.ndarray:
    return np.vstack([np.frombuffer(p, np.float64).reshape(-1, m) for p in parts])


def tsqr(df: DataFrame, cols: list[str], fan: int = FAN) -> np.ndarray:
    """The R of the QR of a tall matrix with rows in ``df``: each task reduces its rows to a triangle (as many as there are shuffle
    partitions, at most), tasks combine ``fan`` triangles each until at most ``fan`` are left for the driver."""
    m, level = len(cols), int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        r = np.zeros((0, m))
        for batch in batches:
            rows = np.column_stack([c.to_numpy(zero_copy_only=False) for c in batch.columns]) if batch.num_rows else np.zeros((0, m))
            r = np.linalg.qr(np.vstack([r, rows]), mode="r")
        if r.shape[0]:
            yield pa.RecordBatch.from_arrays([pa.array([r.tobytes()], pa.binary())], names=["r"])

    def merge(t: pa.Table) -> pa.Table:
        return pa.table([pa.array([np.linalg.qr(_stack(t.column("r").to_pylist(), m), mode="r").tobytes()], pa.binary())], names=["r"])

    parts = df.select(*cols).coalesce(level).mapInArrow(local, "r binary")
    while level > fan:
        level = -(-level // fan)
        parts = parts.withColumn("g", F.pmod(F.spark_partition_id(), F.lit(level))).groupBy("g").applyInArrow(merge, "r binary")
    rows = [bytes(r.r) for r in parts.collect()]  # at most ``fan`` triangles
    return np.linalg.qr(_stack(rows, m), mode="r") if rows else np.zeros((m, m))


def combine(df: DataFrame, c: np.ndarray, cols: list[str], names: list[str] | None = None) -> DataFrame:
    """X C as columns; C is small and becomes literals."""
    c = np.asarray(c, np.float64).reshape(len(cols), -1)
    names = names or columns(c.shape[1])
    return df.select("state", *(sum((F.col(x) * F.lit(float(v)) for x, v in zip(cols, c[:, j], strict=True)), F.lit(0.0)).alias(n) for j, n in enumerate(names)))


def side_by_side(blocks: list[DataFrame]) -> tuple[DataFrame, list[list[str]]]:
    """Blocks of one chain joined on the state; the column names of each."""
    out, names = [], []
    for age, b in enumerate(blocks):
        cols = columns(width_of(b))
        names.append([f"b{age}_{c}" for c in cols])
        out.append(b.select("state", *(F.col(c).alias(n) for c, n in zip(cols, names[-1], strict=True))))
    joined = reduce(lambda x, y: x.join(y, "state", "full_outer"), out)
    every = [c for n in names for c in n]
    return joined.select("state", *(F.coalesce(c, F.lit(0.0)).alias(c) for c in every)), names


def extract_window(blocks: list[DataFrame], how: str = "min_residual", image: DataFrame | None = None, rtol: float = smalldense.RANK_RTOL) -> tuple[smalldense.Extraction, DataFrame]:
    """(extraction, vector (state, x0)) from consecutive blocks, oldest first.

    Shifted image (default): the window is all but the last block and its image all but the first, so no extra pass is made.
    Explicit image: ``blocks`` is the whole basis and ``image`` (columns in the same order, x0 ..) its product.
    """
    if image is None:
        table, names = side_by_side(blocks)
        basis, moved = [c for n in names[:-1] for c in n], [c for n in names[1:] for c in n]
    else:
        both, names = side_by_side([*blocks, image])
        table, basis, moved = both, [c for n in names[:-1] for c in n], names[-1]
    norms = table.agg(*(F.sqrt(F.sum(F.col(c) * F.col(c))).alias(c) for c in basis)).first()
    scale = np.array([max(float(norms[c] or 0.0), 1e-300) for c in basis])
    wide = table.select("state", *((F.col(c) / float(s)).alias(f"w{i}") for i, (c, s) in enumerate(zip(basis, scale, strict=True))), *((F.col(c) / float(s)).alias(f"z{i}") for i, (c, s) in enumerate(zip(moved, scale, strict=True))))
    r = tsqr(wide, [f"w{i}" for i in range(len(basis))] + [f"z{i}" for i in range(len(basis))])
    found = smalldense.EXTRACTIONS[how](r, scale, rtol)
    return found, combine(table, found.coefficients[:, None], basis, ["x0"])
