"""Mixing of sources to target weights, by hash-random keys and distributed prefix sums.

Each row gets a key from a hash of its id, uniform in [0, 1). Within a source rows are cut into
ranges of the key; sums of ranges are added up over the few ranges of a source, and rows only
within their range, so no task ever holds a whole source. A source whose target is above its size
is taken whole that many times, and the rest goes to the rows before the cut.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from latticewalk.llm.common import WORD, n_groups


def source_targets(sizes: DataFrame, share: float, most: float, weights: Sequence[int]) -> DataFrame:
    """sizes: source, source_size. Adds target: shares by weight of `share` of all sizes, each at most `most` of its own size.

    Sources by code point, null last, get the weights in turn. Filling up is solved at once: in order of
    size for weight, the level is what is left for the weights that are left; sources below it are full. It
    rises while sources fill and falls after, so the level of the first that does not fill is the largest of those.
    One row a source; the table of sources is all that meets in one task.
    """
    order = Window.orderBy(F.col("source").isNull(), F.encode("source", "utf-8"))
    w = sizes.withColumn("w", F.element_at(F.array(*map(F.lit, weights)), F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1))
    w = w.withColumn("cap", most * F.col("source_size"))
    by = Window.orderBy(F.col("cap") / F.col("w"), F.col("source").isNull(), "source").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    every = Window.partitionBy()
    w = w.withColumn("filled", F.sum("cap").over(by) - F.col("cap")).withColumn("open", F.sum("w").over(every) - F.sum("w").over(by) + F.col("w"))
    w = w.withColumn("level", (share * F.sum("source_size").over(every) - F.col("filled")) / F.col("open"))
    w = w.withColumn("final", F.max(F.when(F.col("level") * F.col("w") < F.col("cap"), F.col("level"))).over(every))
    return w.select("source", "source_size", F.coalesce(F.least("cap", F.col("final") * F.col("w")), "cap").alias("target"))


def mix(docs: DataFrame, share: float = 1.5, most: float = 2.0, weights: Sequence[int] = (5, 2, 1), seed: str = "mix", range_rows: int = 8_000) -> DataFrame:
    """All rows of docs with columns size, source_size, target, copies, taken added (replacing columns of these names).

    size: words of the text (null: 0). copies: how often the mix takes the document, taken: its words in all.
    The last epoch takes the documents before the source's cut; the one that the cut goes through is taken if
    most of it is before the cut. A null source is a source. Keys are of id and text, so rows of one id, or without
    any, are dealt over all ranges; rows that repeat both count each and are alike, so reruns agree whichever of them
    are before the cut. An empty table gives no rows.
    """
    own = docs.drop("size", "source_size", "target", "copies", "taken").withColumn("size", F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long"))
    ranges = n_groups(docs.count(), range_rows)
    text = F.md5(F.coalesce(F.col("text"), F.lit("")).cast("binary"))
    key = F.md5(F.concat(F.lit(seed + ":"), F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit(":"), text).cast("binary"))
    own = own.withColumn("__key", key).withColumn("__range", F.floor(F.conv(F.substring("__key", 1, 8), 16, 10).cast("long") * ranges / 4294967296).cast("int"))
    sums = own.groupBy("source", "__range").agg(F.sum("size").alias("__sum"))
    before = Window.partitionBy("source").orderBy("__range").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    sums = sums.withColumn("__before", F.sum("__sum").over(before) - F.col("__sum"))
    targets = source_targets(sums.groupBy("source").agg(F.sum("__sum").alias("source_size")), share, most, weights)
    plan = sums.alias("r").join(targets.alias("t"), F.expr("r.source <=> t.source")).selectExpr("r.source as __source", "r.__range as __r", "__before", "source_size", "target")
    inside = Window.partitionBy("source", "__range").orderBy("__key", "size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    own = own.withColumn("__inside", F.sum("size").over(inside) - F.col("size"))
    own = own.join(plan, F.expr("source <=> __source and __range = __r"))
    epochs = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0))
    own = own.withColumn("copies", epochs.cast("int"))
    rest = F.col("target") - F.col("copies") * F.col("source_size")
    last = (F.col("__before") + F.col("__inside") + F.col("size") / 2 <= rest) & (rest > 0)
    own = own.withColumn("copies", F.col("copies") + F.when(last, 1).otherwise(0))
    return own.withColumn("taken", F.col("copies") * F.col("size")).drop("__key", "__range", "__inside", "__before", "__source", "__r")


def mixed_rows(docs: DataFrame, **how) -> DataFrame:
    """The mix itself: the columns of docs, each document as many times as it is taken."""
    columns = docs.columns
    return mix(docs, **how).withColumn("__copy", F.explode(F.expr("if(copies > 0, sequence(1, copies), cast(array() as array<int>))"))).select(*columns)


#: The same in SQL, for the contract's parameters.
ORACLE = r"""
with own as (select doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint as size, md5('mix:' || coalesce(doc_id::varchar, '') || ':' || md5(coalesce(text, ''))) as k from documents),
s as (select source, sum(size)::bigint as source_size from own group by source),
n as (select *, [5, 2, 1][((row_number() over (order by source is null, source)) - 1) % 3 + 1] as w from s),
c as (select *, 2.0::double * source_size as cap from n),
f as (select *, sum(cap) over by_fill - cap as filled, sum(w) over () - sum(w) over by_fill + w as open, sum(source_size) over () as total from c
      window by_fill as (order by cap / w, source is null, source rows between unbounded preceding and current row)),
l as (select *, (1.5::double * total::double - filled) / open::double as level from f),
m as (select *, max(case when level * w < cap then level end) over () as final from l),
t as (select source, source_size, coalesce(least(cap, final * w), cap) as target, case when source_size > 0 then floor(coalesce(least(cap, final * w), cap) / source_size) else 0 end as epochs from m),
p as (select o.*, t.source_size, t.target, t.epochs, sum(o.size) over (partition by o.source order by o.k, o.size rows between unbounded preceding and current row) - o.size as before
      from own o join t on o.source is not distinct from t.source)
select doc_id, size, source_size, target, (size * (epochs + case when target - epochs * source_size > 0 and before + size / 2.0::double <= target - epochs * source_size then 1 else 0 end))::bigint as taken from p
"""
