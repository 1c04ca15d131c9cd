"""Writers of what the engine makes: graph databases, supports, releases and ledgers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def write_packed(packed: DataFrame, path: str, files: int | None = None) -> None:
    """Packed graphs as Parquet, dealt and sorted by gid, so that a reader prunes by gid and a job reads even files."""
    dealt = packed.repartition(files, "gid") if files else packed
    dealt.sortWithinPartitions("gid").write.mode("overwrite").parquet(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, by: str = "gid") -> None:
    """A table bucketed by gid: matching by joins on gid then needs no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(table)


def write_supports(supports: DataFrame, path: str) -> None:
    """The table of supports, which is as secret as the data: it never is part of a release."""
    supports.select("pattern_key", "support").write.mode("overwrite").parquet(path)


def write_release(release, spark, path: str) -> None:
    """The patterns that leave and the ledger of what they cost, as JSON; no trace and no true support."""
    release.to_df(spark).coalesce(1).write.mode("overwrite").json(f"{path}/patterns")
    release.ledger.to_df(spark).coalesce(1).write.mode("overwrite").json(f"{path}/ledger")


def write_graph_text(packed: DataFrame, path: str) -> None:
    """Packed graphs in lines `t # id`, `v id label`, `e u v label` (label 0); read_graph_text reads them back."""
    vertices = "transform(vlabel, (l, i) -> concat('v ', i, ' ', l))"
    edges = "transform(arrays_zip(src, dst), e -> concat('e ', e.src, ' ', e.dst, ' 0'))"
    lines = F.expr(f"array_join(concat(array(concat('t # ', gid)), {vertices}, {edges}), '\\n')")
    packed.select(lines.alias("value")).write.mode("overwrite").text(path)
