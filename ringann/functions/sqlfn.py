"""Functions for SQL: scalar, aggregate and table functions, registered by `register_all`."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import SparkSession
from pyspark.sql.functions import arrow_udf, pandas_udf, udtf

from ringann.functions import runs
from ringann.operators.probe import perturbations


def _pairs(a: pa.Array, b: pa.Array, f) -> pa.Array:
    """f(rows of a, rows of b) of all pairs of the same length at once; null where either is null, an error where lengths differ."""
    size = lambda c: pc.fill_null(pc.list_value_length(c), -1).to_numpy(zero_copy_only=False)
    if pa.types.is_null(a.type) or pa.types.is_null(b.type):
        return pa.nulls(len(a), pa.int32())
    left, right = size(a), size(b)
    none = (left < 0) | (right < 0)
    if (left != right)[~none].any():
        raise ValueError("code strings of different lengths")
    out = np.zeros(len(left), np.int32)
    for m in np.unique(left[~none & (left > 0)]):
        at = np.flatnonzero(~none & (left == m))
        rows = lambda c: (c if len(at) == len(c) else c.take(pa.array(at))).flatten().to_numpy(zero_copy_only=False).reshape(len(at), m)  # noqa: E731, B023
        out[at] = f(rows(a), rows(b))
    return pa.array(out, mask=none)


def run_len(a: pa.Array, b: pa.Array) -> pa.Array:
    return _pairs(a, b, runs.run_lengths)


def equal_positions(a: pa.Array, b: pa.Array) -> pa.Array:
    return _pairs(a, b, lambda x, y: (x == y).sum(axis=1))


def kth(dist: pd.Series, k: pd.Series) -> float:
    """The k-th smallest of a group, or its largest if it is smaller."""
    near = np.sort(dist.dropna().to_numpy())[: int(k.iloc[0])]
    return float(near[-1]) if len(near) else float("nan")


class Rotations:
    """All rotations of a code string; none of null."""

    def eval(self, codes):
        for i in range(len(codes or [])):
            yield i, list(codes[i:]) + list(codes[:i])


class Perturbations:
    """Probes of ascending score, from scores by position and alternative."""

    def eval(self, scores, n_probes: int):
        for i, (delta, score) in enumerate(perturbations(np.array(scores, float), n_probes)):
            yield i, float(score), [p for p, _ in delta], [a for _, a in delta]


def register_all(spark: SparkSession) -> None:
    """ring_run_len, ring_equal_positions, ring_kth; table functions ring_rotations, ring_perturbations."""
    spark.udf.register("ring_run_len", arrow_udf(run_len, "int"))
    spark.udf.register("ring_equal_positions", arrow_udf(equal_positions, "int"))
    spark.udf.register("ring_kth", pandas_udf(kth, "double"))
    spark.udtf.register("ring_rotations", udtf(Rotations, returnType="rot: int, s: array<int>"))
    spark.udtf.register("ring_perturbations", udtf(Perturbations, returnType="probe_no: int, score: double, positions: array<int>, places: array<int>"))
