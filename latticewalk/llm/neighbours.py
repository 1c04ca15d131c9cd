"""Approximate nearest neighbours by cosine, with cross-polytope hashing.

Each table rotates unit vectors by sign flips and fast Hadamard transforms (three rounds) and assigns
them to the nearest signed axis. A query looks into the buckets of its nearest few axes in every table.
Buckets are cut into blocks of bounded size; a query meets the rows of a block in one task, keeps its
best there by exact cosine on the original vectors, and the best of all blocks are merged. Queries that
find fewer than they want meet all rows. A bucket has few of those, so they don't grow with the table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from latticewalk.llm.common import cut


def hadamard(x: np.ndarray) -> np.ndarray:
    """The fast Hadamard transform of the rows of x, whose width is a power of two, scaled to keep lengths."""
    n, d = x.shape
    h = 1
    while h < d:
        x = x.reshape(n, d // (2 * h), 2, h)
        x = np.stack([x[:, :, 0] + x[:, :, 1], x[:, :, 0] - x[:, :, 1]], axis=2)
        h *= 2
    return x.reshape(n, d) / np.sqrt(d)


def rotated(x: np.ndarray, number: int, seed: int) -> np.ndarray:
    """A pseudo-random rotation of rows (padded to a power of two), the same for a seed and a number everywhere."""
    width = 1 << max(1, int(x.shape[1] - 1).bit_length())
    x = np.pad(x, ((0, 0), (0, width - x.shape[1])))
    signs = np.random.default_rng([seed, number]).choice([-1.0, 1.0], size=(3, width))
    for s in signs:
        x = hadamard(x * s)
    return x


def axes(x: np.ndarray, probes: int) -> np.ndarray:
    """The nearest signed axes of each row, nearest first: 2 * axis, plus one for the negative side."""
    size = np.abs(x)
    best = np.argsort(-size, axis=1, kind="stable")[:, :probes]
    return 2 * best + (np.take_along_axis(x, best, 1) < 0)


def usable(batch: pd.Series, ids: pd.Series) -> tuple[np.ndarray, list]:
    """Vectors that take part, as doubles, and their positions."""
    at, rows = [], []
    for i, (v, k) in enumerate(zip(batch, ids, strict=True)):
        if v is None or pd.isna(k) or not len(v):
            continue
        try:
            x = np.array(v, dtype=np.float64)
        except (TypeError, ValueError):
            continue
        if np.isfinite(x).all() and x.any():
            at.append(i)
            rows.append(x)
    return rows, at


def dtype_of(vectors: DataFrame) -> type:
    return np.float32 if vectors.schema["embedding"].dataType.simpleString() == "array<float>" else np.float64


def hashed(vectors: DataFrame, tables: int, probes: int, seed: int) -> DataFrame:
    """vec_id, bucket (of table, width and axis) and the vector as bytes, a row for each table and probe.

    The bytes are of the column's own type, which holds the vector exactly: single precision is half as much to move.
    """
    kind = dtype_of(vectors)

    def spread(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows, at = usable(batch["embedding"], batch["vec_id"])
            ids = batch["vec_id"].to_numpy()[at].astype(np.int64) if at else np.zeros(0, np.int64)
            for width in sorted({len(r) for r in rows}):
                pick = [i for i, r in enumerate(rows) if len(r) == width]
                x = np.stack([rows[i] for i in pick])
                unit = x / np.abs(x).max(axis=1, keepdims=True)
                unit /= np.sqrt((unit * unit).sum(axis=1, keepdims=True))
                raw = [r.tobytes() for r in x.astype(kind)]
                for t in range(tables):
                    a = axes(rotated(unit, t, seed), probes)
                    for p in range(a.shape[1]):
                        yield pd.DataFrame({"vec_id": ids[pick], "bucket": (width * tables + t) * (1 << 20) + a[:, p].astype(np.int64), "vector": raw})

    return vectors.select(F.col("vec_id").cast("long").alias("vec_id"), "embedding").mapInPandas(spread, "vec_id long, bucket long, vector binary")


def cosines(query: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Cosines in double precision; equal rows get equal values, wherever they stand."""
    return (rows * query).sum(axis=1) / (np.sqrt((rows * rows).sum(axis=1)) * np.sqrt((query * query).sum()))


def nearest(vectors: DataFrame, k: int = 5, every: int = 50, tables: int = 8, probes: int = 10, block_rows: int = 4096, seed: int = 11) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest found of each row whose vec_id is divisible by `every`.

    All candidates where there are no more than k; the exact k nearest where the tables find fewer.
    Vectors that are null, zero, empty or hold null or non-finite components, and rows with a null id, take no
    part. Vectors of other lengths than the query's aren't comparable and aren't candidates. Ties go to the smaller
    vec_id; a row that repeats a vec_id with the same vector counts once. Other columns are left out.
    """
    own, kind = vectors.select("vec_id", "embedding").distinct(), dtype_of(vectors)
    index = cut(hashed(own, tables, 1, seed))
    asked = cut(hashed(own.where(F.pmod("vec_id", F.lit(every)) == 0), tables, probes, seed))
    part = lambda name: F.pmod(F.xxhash64("vec_id"), F.col(name).cast("long"))
    each = lambda name: F.explode(F.sequence(F.lit(0).cast("long"), F.col(name).cast("long") - 1))

    def search(key: tuple, queries: pd.DataFrame, rows: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(queries) and len(rows):
            ids = rows["vec_id"].to_numpy()
            order = np.argsort(ids, kind="stable")
            ids = ids[order]
            x = np.stack([np.frombuffer(v, kind) for v in rows["vector"]])[order].astype(np.float64)
            for q, v in zip(queries["vec_id"], queries["vector"], strict=True):
                s = cosines(np.frombuffer(v, kind).astype(np.float64), x)
                s[ids == q] = -np.inf
                if len(s) > k:
                    edge = np.partition(s, -k)[-k]
                    best = np.flatnonzero(s >= edge)
                else:
                    best = np.arange(len(s))
                best = best[np.lexsort((ids[best], -s[best]))][:k]
                out += [(q, ids[i], s[i]) for i in best if s[i] > -np.inf]
        return pd.DataFrame(out, columns=["query_id", "vec_id", "score"])

    def meet(queries: DataFrame, rows: DataFrame) -> DataFrame:
        """The best of each query in each block of the rows in its bucket."""
        size = lambda df, name: df.groupBy("bucket").agg(F.ceil(F.count("*") / block_rows).cast("int").alias(name))
        blocks = cut(size(rows, "blocks").join(size(queries, "query_blocks"), "bucket"))
        placed = rows.join(blocks, "bucket").withColumn("block", part("blocks")).withColumn("query_block", each("query_blocks"))
        queries = queries.join(blocks, "bucket").withColumn("query_block", part("query_blocks")).withColumn("block", each("blocks"))
        on = ("bucket", "block", "query_block")
        return queries.groupBy(*on).cogroup(placed.groupBy(*on)).applyInPandas(search, "query_id long, vec_id long, score double")

    found = cut(meet(asked, index).groupBy("query_id", "vec_id").agg(F.max("score").alias("score")))
    # those with fewer than k (each block keeps its k best, so k are left where there are k) meet all rows of their width
    first = lambda df: df.where(F.pmod(F.shiftright("bucket", 20), F.lit(tables)) == 0).withColumn("bucket", F.floor(F.shiftright("bucket", 20) / tables))
    enough = found.groupBy("query_id").agg(F.count("*").alias("n")).where(F.col("n") >= k).select(F.col("query_id").alias("vec_id"))
    short = cut(first(asked).distinct().join(enough, "vec_id", "left_anti"))
    found = found.unionByName(meet(short, first(index))).groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    rank = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(rank)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
