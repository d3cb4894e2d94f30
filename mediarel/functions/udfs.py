"""The engine's functions as Python UDFs, for models and libraries that have no column form.

The column expressions of ``functions.geometry`` are the fast way; these are their vectorised twins on Arrow batches.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import functions as F


@F.arrow_udf("double")
def cosine_batch(a: pa.Array, b: pa.Array) -> pa.Array:
    """Cosine of paired vectors of one length; null where one is null or zero."""
    left, right = (np.array([np.asarray(v, dtype=float) if v is not None else np.zeros(0) for v in x.to_pylist()], dtype=object) for x in (a, b))
    out = []
    for x, y in zip(left, right, strict=True):
        size = np.linalg.norm(x) * np.linalg.norm(y) if len(x) and len(x) == len(y) else 0.0
        out.append(float(x @ y / size) if size else None)
    return pa.array(out, pa.float64())


@F.pandas_udf("double")
def box_iou_batch(ax: pd.Series, ay: pd.Series, aw: pd.Series, ah: pd.Series, bx: pd.Series, by: pd.Series, bw: pd.Series, bh: pd.Series) -> pd.Series:
    """IoU of paired boxes (x, y, w, h)."""
    wide = (np.minimum(ax + aw, bx + bw) - np.maximum(ax, bx)).clip(lower=0)
    high = (np.minimum(ay + ah, by + bh) - np.maximum(ay, by)).clip(lower=0)
    both = wide * high
    whole = aw * ah + bw * bh - both
    return (both / whole.where(whole > 0, 1.0)).where(whole > 0, 0.0)


@F.pandas_udf("array<double>")
def vector_mean(v: pd.Series) -> list[float]:
    """Element-wise mean of a group's vectors. The group meets in one task: for large groups group the positions instead."""
    return np.mean(np.stack([np.asarray(x, dtype=float) for x in v]), axis=0).tolist()


@F.pandas_udf("bigint")
def union_ms(start: pd.Series, end: pd.Series) -> int:
    """Length of the union of a group's intervals."""
    total, reach = 0, None
    for a, b in sorted(zip(start, end, strict=True)):
        if reach is None or a > reach:
            total, reach = total + b - a, b
        elif b > reach:
            total, reach = total + b - reach, b
    return int(total)
