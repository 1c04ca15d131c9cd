"""Functions for SQL and DataFrame users: keys of patterns and containment, in Arrow batches."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, StringType

from latticewalk.functions.pattern import adjacency, canonical_key, clean, contains, parse_key


@F.pandas_udf(StringType())
def pattern_key(labels: pd.Series, src: pd.Series, dst: pd.Series) -> pd.Series:
    """The canonical key of a pattern given by labels of vertices and ends of edges (arrays); null if any of them is."""

    def key(ls, us, vs) -> str | None:
        if ls is None or us is None or vs is None:
            return None
        edges = {(min(u, v), max(u, v)) for u, v in zip(us.tolist(), vs.tolist(), strict=True)}
        return canonical_key(tuple(ls.tolist()), tuple(sorted(edges)))

    return pd.Series([key(*row) for row in zip(labels, src, dst, strict=True)], dtype=object)


def contains_pattern(key: str, labels: str = "vlabel", src: str = "src", dst: str = "dst") -> Column:
    """Whether the packed graph of a row holds a pattern; a row without a graph holds none."""
    p = parse_key(key)

    @F.pandas_udf(BooleanType())
    def test(ls: pd.Series, us: pd.Series, vs: pd.Series) -> pd.Series:
        found = []
        for a, b, c in zip(ls, us, vs, strict=True):
            whole = a is not None and b is not None and c is not None
            found.append(whole and contains(clean(a.tolist()), adjacency(len(a), b.tolist(), c.tolist()), p))
        return pd.Series(found, dtype=bool)

    return test(labels, src, dst)


def register(spark: SparkSession) -> None:
    """pattern_key(labels, src, dst) in SQL."""
    spark.udf.register("pattern_key", pattern_key)
