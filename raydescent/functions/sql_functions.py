"""Functions and table functions for SQL."""

from __future__ import annotations

from collections.abc import Iterator
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from raydescent.plans.models import NetSpec, forward, softmax
from raydescent.plans.params import CodeParams, embed_parameters


def register(spark: SparkSession) -> None:
    """char_sign, dot, softmax, ray_angle and array_total as SQL functions without Python; code_rows and wave_rows as table functions."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION char_sign(a INT, b INT) RETURNS INT RETURN 1 - 2 * (bit_count(a & b) % 2)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION softmax(z ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN transform(z, x -> exp(x - array_max(z)) / aggregate(z, 0D, (s, y) -> s + exp(y - array_max(z))))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION ray_angle(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN acos(least(1D, abs(aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)) / sqrt(aggregate(a, 0D, (s, x) -> s + x * x) * aggregate(b, 0D, (s, x) -> s + x * x))))")

    @F.udtf(returnType="lane int, theta int, sign int, scale double")
    class CodeRows:
        def eval(self, k: int, t: int):
            p = CodeParams(2 * k, k, t).validate()
            for lane in range(p.n):
                for q in range(t):
                    yield lane, p.theta(lane, q), p.sign(lane, q), t**-0.5

    @F.udtf(returnType="wave int, lane int, code_row int, slot int, code_col int, task int, sign int")
    class WaveRows:
        def eval(self, n: int, k: int, t: int, waves: int):
            e = embed_parameters(n, k, t)
            lanes = min(e.rows, 2 * e.cols)
            code = CodeParams(lanes, e.cols, t)
            for wave in range(waves):
                for lane in range(n):
                    row = (lane + wave * e.step) % e.rows
                    on = {code.theta(row % lanes, q): code.sign(row % lanes, q) for q in range(t)}
                    for slot in range(k):
                        col = (slot + wave) % e.cols
                        if col in on:
                            yield wave, lane, row, slot, col, (slot + wave) % k, on[col]

    @F.pandas_udf("array<double>")
    def array_total(values: pd.Series) -> Any:
        """The element-wise sum of a group's arrays without null ones. For small groups: large ones go through gradients.summed()."""
        rows = [np.asarray(v, float) for v in values if v is not None]
        return np.sum(rows, axis=0).tolist() if rows else []

    spark.udtf.register("code_rows", CodeRows)
    spark.udtf.register("wave_rows", WaveRows)
    spark.udf.register("array_total", array_total)


def predict(df: DataFrame, spec: NetSpec, weights: list[np.ndarray], x_col: str = "x") -> Column:
    """A column with the predicted class (or value, or probability for two classes) of each row; null for a null x."""
    held = df.sparkSession.sparkContext.broadcast(weights)

    @F.pandas_udf("double")
    def score(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for x in batches:
            out = pd.Series([None] * len(x), dtype="float64")
            at = x.notna().to_numpy().nonzero()[0]
            if len(at):
                _, s = forward(spec, held.value, np.stack([np.asarray(v, float) for v in x.iloc[at]]))
                if spec.loss == "mse_linear":
                    got = s[:, 0]
                elif spec.loss == "xent_logistic":
                    got = 1 / (1 + np.exp(-s[:, 0]))
                else:
                    got = softmax(s, spec.softmax_form).argmax(axis=1)
                out.iloc[at] = got
            yield out

    return score(F.col(x_col))
