"""Convergence diagnostics of many chains at once (D12-D14), over series in a DataFrame, by the walk's own tests."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from latticewalk.operators import walk


def geweke(series: DataFrame, first: float = 0.1, last: float = 0.5, var: str = "sample") -> DataFrame:
    """D12. chain, z of each series (chain, at, value); `at` puts a series in order. A chain's length is bounded by max_steps."""

    def z(rows: pd.DataFrame) -> pd.DataFrame:
        x = rows.sort_values("at")["value"].tolist()
        return pd.DataFrame({"chain": [rows["chain"].iloc[0]], "n": [len(x)], "z": [walk.geweke_z(x, first, last, var)]})

    return series.select("chain", "at", "value").groupBy("chain").applyInPandas(z, "chain long, n long, z double")


def converged(series: DataFrame, run: int = 20, bound: float = 1.0) -> DataFrame:
    """D13. chain, at, converged: whether at this step the test has held for `run` steps in a row."""

    def flags(rows: pd.DataFrame) -> pd.DataFrame:
        rows, test = rows.sort_values("at"), walk.Convergence(1, run, bound)
        return pd.DataFrame({"chain": rows["chain"], "at": rows["at"], "converged": [test.add((x,)) for x in rows["value"]]})

    return series.select("chain", "at", "value").groupBy("chain").applyInPandas(flags, "chain long, at long, converged boolean")


def scale_reduction(values: DataFrame) -> DataFrame:
    """D14. r_hat of chains of any lengths (chain, value), as walk.gelman_rubin; only sums of each chain are shuffled."""
    c = values.where("chain is not null").groupBy("chain").agg(F.count("value").alias("n"), F.avg("value").alias("m"), F.var_samp("value").alias("v")).where("n > 1")
    t = c.agg(F.avg("n").alias("n"), (F.sum(F.expr("n * m")) / F.sum("n")).alias("mean"), (F.sum(F.expr("(n - 1) * v")) / F.sum(F.expr("n - 1"))).alias("w"))
    spread = (F.sum(F.expr("own * (m - mean) * (m - mean)")) / (F.count("*") - 1)).alias("b")
    b = c.select(F.col("n").alias("own"), "m").crossJoin(F.broadcast(t)).groupBy("n", "w").agg(spread)
    return b.select(F.sqrt(((F.col("n") - 1) / F.col("n") * F.col("w") + F.col("b") / F.col("n")) / F.col("w")).alias("r_hat"))
