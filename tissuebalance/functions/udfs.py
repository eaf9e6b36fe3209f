"""The engine's functions for SQL users: pandas functions, a table function, and SQL functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from . import balance, gru


def residuals(w: gru.Weights, xs: np.ndarray) -> list[float]:
    """The residual after each input of one boundary, from a fresh state."""
    h, out = np.zeros((1, gru.HIDDEN)), []
    for x in xs:
        h, r = gru.step(np.asarray(x, float)[None, :], h, w)
        out.append(float(r[0]))
    return out


def gru_residual(w: gru.Weights):
    """A pandas function from a boundary's inputs over time (arrays of 12) to its residuals."""
    text = gru.dumps(w)

    @F.pandas_udf("array<double>")
    def run(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        weights = gru.loads(text)
        for part in parts:
            yield part.map(lambda xs: residuals(weights, xs))

    return run


def imbalance():
    """A pandas aggregate: the global imbalance of a group's times."""

    @F.pandas_udf("double")
    def run(times: pd.Series) -> float:
        return float(balance.global_imbalance(times.to_numpy(float)))

    return run


class Stencil:
    """Table function: the bin itself and the 26 around it."""

    def eval(self, bx: int, by: int, bz: int):
        for i in (-1, 0, 1):
            for j in (-1, 0, 1):
                for k in (-1, 0, 1):
                    yield bx + i, by + j, bz + k


PROPOSAL = """CREATE OR REPLACE TEMPORARY FUNCTION reactive_proposal(t_left DOUBLE, t_right DOUBLE, n_left DOUBLE, n_right DOUBLE, tau DOUBLE, alpha DOUBLE) RETURNS DOUBLE
RETURN CASE WHEN abs((t_right - t_left) / ((t_right + t_left) / 2)) > tau
  THEN signum(t_right - t_left) * alpha * if(t_right > t_left, n_right, n_left) * abs(t_right - t_left) / (2 * greatest(t_left, t_right)) ELSE 0D END"""
COMBINED = """CREATE OR REPLACE TEMPORARY FUNCTION combined_step(proposal DOUBLE, residual DOUBLE, most DOUBLE) RETURNS DOUBLE
RETURN most * tanh(atanh(least(greatest(proposal / most, -1 + 1e-6D), 1 - 1e-6D)) + residual)"""


def register(spark: SparkSession) -> None:
    """reactive_proposal, combined_step, gru_residual, imbalance and stencil, by name in the session's SQL."""
    spark.sql(PROPOSAL)
    spark.sql(COMBINED)
    spark.udf.register("gru_residual", gru_residual(gru.trained()))
    spark.udf.register("imbalance", imbalance())
    spark.udtf.register("stencil", F.udtf(Stencil, returnType="bx bigint, by bigint, bz bigint"))


def numbers(values: np.ndarray) -> str:
    return "array(" + ", ".join(f"{float(v)!r}D" for v in values) + ")"


def sql_residuals(w: gru.Weights, xs: str) -> Column:
    """The same residuals as one fold in SQL, without Python: xs is an array of arrays of 12."""
    n = gru.HIDDEN
    inputs = w["w_x"].shape[0]

    def gates(v: str, name: str, weights: np.ndarray, bias: np.ndarray, size: int) -> str:
        """let name be the 3n numbers weights' v + bias."""
        rows = f"transform(sequence(0, {3 * n - 1}), j -> aggregate(sequence(0, {size - 1}), {numbers(bias)}[j], (u, i) -> u + {v}[i] * {numbers(weights.T.ravel())}[j * {size} + i]))"
        return f"transform(array({rows}), {name} -> "

    fresh = f"tanh(a[k + {2 * n}] + z[k + {2 * n}] / (1 + exp(-(a[k] + z[k]))))"
    update = f"(1 / (1 + exp(-(a[k + {n}] + z[k + {n}]))))"
    state = f"transform(sequence(0, {n - 1}), k -> (1 - {update}) * {fresh} + {update} * s.h[k])"
    out = f"aggregate(sequence(0, {n - 1}), {float(w['bias'][0])!r}D, (u, i) -> u + h[i] * {numbers(w['head'][:, 0])}[i])"
    step = f"transform(array({state}), h -> named_struct('h', h, 'out', concat(s.out, array({out}))))[0]"
    step = gates("x", "a", w["w_x"], w["b_x"], inputs) + gates("s.h", "z", w["w_h"], w["b_h"], n) + f"{step})[0])[0]"
    start = f"named_struct('h', array_repeat(0D, {n}), 'out', cast(array() as array<double>))"
    return F.expr(f"aggregate({xs}, {start}, (s, x) -> {step}, s -> s.out)")
