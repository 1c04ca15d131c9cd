"""Graph databases from the given tables, as vertices(gid, vid, label) and edges(gid, src, dst), src < dst."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from html.parser import HTMLParser

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

CLICK = ("click", "error", "purchase", "signup", "view")
DENSE = ("AF", "AO", "NF", "NO", "RF", "RO")
SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")
PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")
PROFILE = (*SEGMENTS, *PRIORITIES, "A", "N", "R")
ROLES = ("system", "user", "assistant")
EGO = tuple(map(str, range(10)))
#: Declared element names; other elements take no part, their children hang on the nearest declared ancestor.
TAGS = ("a", "article", "b", "body", "br", "div", "footer", "h1", "head", "html", "li", "meta", "nav", "p", "script", "style", "title", "ul")
VOID = frozenset(("area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "source", "track", "wbr"))
#: User ids times this, plus the number of the session.
SESSIONS = 1_000_000


@dataclass
class GraphTables:
    vertices: DataFrame
    edges: DataFrame
    names: tuple[str, ...]


def label(column, names):
    """The number of a name among the public ones; other names are null."""
    return F.nullif(F.array_position(F.array(*map(F.lit, names)), column), F.lit(0)).cast("int") - 1


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def sessions(events: DataFrame, gap_hours: int = 12) -> DataFrame:
    """Events with gid and vid: a session ends after a pause of more than the gap; sessions of one event are dropped.

    A user's events are put in order day by day, and days are joined by their first and last events, so that no task
    holds all events of a user who never rests; only the events of one session meet, which are one graph.
    """
    e = events.select("user_id", "ts", "event_id", "event_type", F.to_date("ts").alias("day"))
    by_day = Window.partitionBy("user_id", "day").orderBy("ts", "event_id")
    days = e.groupBy("user_id", "day").agg(F.min("ts").alias("first"), F.max("ts").alias("last"))
    days = days.select("user_id", "day", F.lag("last").over(Window.partitionBy("user_id").orderBy("day")).alias("day_before"))
    e = e.withColumn("before", F.lag("ts").over(by_day)).join(days, ["user_id", "day"])
    e = e.withColumn("before", F.coalesce("before", "day_before"))
    e = e.withColumn("starts", F.when(F.col("before").isNull() | (F.col("ts") - F.col("before") > F.expr(f"interval {gap_hours} hours")), 1).otherwise(0))
    whole_day, upto = Window.partitionBy("user_id").orderBy("day"), by_day.rowsBetween(Window.unboundedPreceding, 0)
    counts = e.groupBy("user_id", "day").agg(F.sum("starts").alias("n")).select("user_id", "day", (F.sum("n").over(whole_day) - F.col("n")).alias("sessions_before"))
    e = e.join(counts, ["user_id", "day"]).withColumn("session", F.col("sessions_before") + F.sum("starts").over(upto))
    own = Window.partitionBy("user_id", "session")
    e = e.withColumn("vid", F.row_number().over(own.orderBy("ts", "event_id")) - 1).withColumn("size", F.count("*").over(own))
    e = e.where("size >= 2").withColumn("gid", F.col("user_id") * SESSIONS + F.col("session"))
    return e.select("user_id", "session", "gid", "vid", "ts", "event_id", "event_type")


def click(spark: SparkSession, sf_dir: str) -> GraphTables:
    """W-click. A tree per session: the parent of an event is the latest view before it, else the first event."""
    e = sessions(read(spark, sf_dir, "events"))
    order = Window.partitionBy("user_id", "session").orderBy("vid").rowsBetween(Window.unboundedPreceding, -1)
    view = F.last(F.when(F.col("event_type") == "view", F.col("vid")), ignorenulls=True).over(order)
    edges = e.select("gid", "vid", F.coalesce(view, F.lit(0)).alias("src")).where("vid > 0").select("gid", F.col("src").cast("int"), F.col("vid").cast("int").alias("dst"))
    return GraphTables(e.select("gid", F.col("vid").cast("int").alias("vid"), label(F.col("event_type"), CLICK).alias("label")), edges, CLICK)


def dense(spark: SparkSession, sf_dir: str, min_lines: int = 8, near: int = 27) -> GraphTables:
    """W-dense. Lines of an order; an edge where quantities differ by at most `near`."""
    l = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_shipdate", F.concat("l_returnflag", "l_linestatus").alias("name"))
    own = Window.partitionBy("l_orderkey")
    vid = F.row_number().over(own.orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_shipdate", "name")) - 1
    v = l.withColumn("vid", vid.cast("int")).withColumn("size", F.count("*").over(own)).where(F.col("size") >= min_lines)
    v = v.select(F.col("l_orderkey").alias("gid"), "vid", label(F.col("name"), DENSE).alias("label"), "l_quantity")
    a, b = v.select("gid", F.col("vid").alias("src"), F.col("l_quantity").alias("q")), v.select("gid", F.col("vid").alias("dst"), F.col("l_quantity").alias("r"))
    edges = a.join(b, "gid").where(f"src < dst and abs(q - r) <= {near}").select("gid", "src", "dst")
    return GraphTables(v.select("gid", "vid", "label"), edges, DENSE)


def profile(spark: SparkSession, sf_dir: str, near_days: int = 30) -> GraphTables:
    """W-profile. Customer, orders and lines as a tree, and edges between consecutive orders of at most `near_days`."""
    c = read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("gid"), label(F.col("c_mktsegment"), PROFILE).alias("label"))
    o = read(spark, sf_dir, "orders").select(F.col("o_custkey").alias("gid"), "o_orderkey", "o_orderdate", label(F.col("o_orderpriority"), PROFILE).alias("label"))
    by = Window.partitionBy("gid").orderBy("o_orderdate", "o_orderkey")
    o = o.withColumn("vid", F.row_number().over(by)).withColumn("before", F.lag("o_orderdate").over(by))
    l = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_shipdate", "l_returnflag")
    l = l.join(o.select("gid", "o_orderkey", F.col("vid").alias("src")), F.col("l_orderkey") == F.col("o_orderkey"))
    place = Window.partitionBy("gid").orderBy("src", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_shipdate", "l_returnflag")
    l = l.withColumn("vid", F.row_number().over(place)).join(o.groupBy("gid").agg(F.count("*").alias("n")), "gid").withColumn("vid", F.col("vid") + F.col("n"))
    v = c.select("gid", F.lit(0).alias("vid"), "label").unionByName(o.select("gid", "vid", "label")).unionByName(l.select("gid", "vid", label(F.col("l_returnflag"), PROFILE).alias("label")))
    e = o.select("gid", F.lit(0).alias("src"), F.col("vid").alias("dst")).unionByName(l.select("gid", "src", F.col("vid").alias("dst")))
    e = e.unionByName(o.where(f"datediff(o_orderdate, before) <= {near_days}").select("gid", (F.col("vid") - 1).alias("src"), F.col("vid").alias("dst")))
    whole = lambda df, *cs: df.select("gid", *(F.col(x).cast("int").alias(x) for x in cs))
    return GraphTables(whole(v, "vid", "label"), whole(e, "src", "dst"), PROFILE)


def role_paths(spark: SparkSession, sf_dir: str) -> GraphTables:
    """W-role. Turns of a conversation in order."""
    by = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    t = read(spark, sf_dir, "conversations").select("conv_id", "role", (F.row_number().over(by) - 1).alias("vid"))
    v = t.select(F.col("conv_id").alias("gid"), F.col("vid").cast("int").alias("vid"), label(F.col("role"), ROLES).alias("label"))
    return GraphTables(v, v.where("vid > 0").select("gid", (F.col("vid") - 1).alias("src"), F.col("vid").alias("dst")), ROLES)


class ElementTree(HTMLParser):
    """Elements of a page in order, with the place of each one's parent. `p` and `li` end an open one of their kind."""

    def __init__(self):
        super().__init__()
        self.open_: list[tuple[str, int]] = []
        self.labels: list[int] = []
        self.parents: list[int] = []

    def handle_starttag(self, tag, attrs):
        if tag in ("p", "li"):
            inside = next((i for i in range(len(self.open_) - 1, -1, -1) if self.open_[i][0] in (tag, "div", "article", "ul", "body")), -1)
            if inside >= 0 and self.open_[inside][0] == tag:
                del self.open_[inside:]
        at = self.open_[-1][1] if self.open_ else -1
        if tag in TAGS:
            self.labels.append(TAGS.index(tag))
            self.parents.append(at)
            at = len(self.labels) - 1
        if tag not in VOID:
            self.open_.append((tag, at))

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)

    def handle_endtag(self, tag):
        at = next((i for i in range(len(self.open_) - 1, -1, -1) if self.open_[i][0] == tag), -1)
        if at >= 0:
            del self.open_[at:]


def page_rows(pages: DataFrame) -> DataFrame:
    """gid, vlabel, src, dst: the packed element tree of each page; a page without declared elements has no row."""

    def parse(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for gid, html in batch.itertuples(index=False):
                t = ElementTree()
                t.feed(html or "")
                t.close()
                edges = [(u, v) for v, u in enumerate(t.parents) if u >= 0]
                if t.labels:
                    rows.append((gid, t.labels, [u for u, _ in edges], [v for _, v in edges]))
            yield pd.DataFrame(rows, columns=["gid", "vlabel", "src", "dst"])

    return pages.select(F.col("page_id").alias("gid"), "html").mapInPandas(parse, "gid long, vlabel array<int>, src array<int>, dst array<int>")


def page_trees(spark: SparkSession, sf_dir: str) -> GraphTables:
    """W-page. The element tree of a page, labelled by element name."""
    rows = page_rows(read(spark, sf_dir, "pages"))
    v = rows.select("gid", F.posexplode("vlabel").alias("vid", "label"))
    return GraphTables(v, rows.select("gid", F.explode(F.arrays_zip("src", "dst")).alias("e")).select("gid", "e.src", "e.dst"), TAGS)


def read_graph_text(spark: SparkSession, path: str) -> GraphTables:
    """Graphs in lines `t # id`, `v id label`, `e u v label`. A record is one graph, so large files are split among tasks.

    Edges keep their label in a column elabel, which patterns don't look at. An edge that is repeated counts once.
    """
    whole = spark.read.option("lineSep", "\nt # ").text(path).select(F.regexp_replace("value", r"^\s*t # ", "").alias("g")).where("trim(g) <> ''")
    g = whole.select(F.regexp_extract("g", r"^(\d+)", 1).cast("long").alias("gid"), F.explode(F.split("g", "\n")).alias("line")).withColumn("p", F.split(F.trim("line"), " +"))
    v = g.where("p[0] = 'v'").selectExpr("gid", "cast(p[1] as int) vid", "cast(p[2] as int) label")
    e = g.where("p[0] = 'e'").selectExpr("gid", "least(cast(p[1] as int), cast(p[2] as int)) src", "greatest(cast(p[1] as int), cast(p[2] as int)) dst", "coalesce(try_cast(get(p, 3) as int), 0) elabel")
    return GraphTables(v, e.groupBy("gid", "src", "dst").agg(F.min("elabel").alias("elabel")), ())


#: Ego nets: components whose signs make a cell, neighbours on either side in its order, and the least cosine of an edge.
EGO_SIGNS, EGO_REACH, EGO_NEAR = 3, 12, 0.05


def ego_nets(spark: SparkSession, sf_dir: str, k: int = 9) -> GraphTables:
    """W-ego. A vector and the `k` nearest of those around it, labelled by their labels; edges where the cosine is large.

    Candidates are the EGO_REACH vectors before and after it in the order of one component, within the cell of vectors
    with the same signs of the first ones: a bounded number for each, however many vectors a cell holds. Vectors
    without values are left out. The middle has edges with all; the others with each other from EGO_NEAR on.
    """
    e = read(spark, sf_dir, "embeddings").where("vec_id is not null and size(embedding) > 0 and not exists(embedding, x -> x is null or isnan(x))")
    e = e.select("vec_id", "label", F.col("embedding").cast("array<double>").alias("x")).where("exists(x, y -> y <> 0)")
    e = e.withColumn("x", F.expr("transform(x, y -> y / sqrt(aggregate(x, 0D, (s, z) -> s + z * z)))"))
    cell = F.concat(*[F.when(F.get("x", F.lit(i)) > 0, "1").otherwise("0") for i in range(EGO_SIGNS)])
    around = Window.partitionBy("cell").orderBy("place", "vec_id").rowsBetween(-EGO_REACH, EGO_REACH)
    e = e.withColumn("cell", cell).withColumn("place", F.get("x", F.lit(EGO_SIGNS)))
    e = e.withColumn("near", F.collect_list(F.struct("vec_id", "label", "x")).over(around))
    cosine = "round(aggregate(zip_with({}, {}, (a, b) -> a * b), 0D, (s, z) -> s + z), 9)"
    ranked = f"transform(filter(near, n -> n.vec_id <> vec_id), n -> struct(-{cosine.format('x', 'n.x')} as far, n.vec_id as vec_id, n.label as label, n.x as x))"
    e = e.withColumn("near", F.expr(f"slice(array_sort({ranked}), 1, {k})"))
    v = e.select(F.col("vec_id").alias("gid"), F.expr("posexplode(concat(array(label), near.label))").alias("vid", "label"))
    own = e.select(F.col("vec_id").alias("gid"), F.explode("near.vec_id").alias("n")).groupBy("gid").agg(F.count("*").alias("n"))
    star = own.select("gid", F.lit(0).alias("src"), F.explode(F.sequence(F.lit(1), F.col("n").cast("int"))).alias("dst"))
    pairs = e.select(F.col("vec_id").alias("gid"), F.posexplode("near").alias("i", "a"), "near").select("gid", "i", "a", F.posexplode("near").alias("j", "b")).where("i < j")
    pairs = pairs.where(f"{cosine.format('a.x', 'b.x')} >= {EGO_NEAR}").select("gid", (F.col("i") + 1).alias("src"), (F.col("j") + 1).alias("dst"))
    return GraphTables(v.select("gid", F.col("vid").cast("int").alias("vid"), F.col("label").cast("int").alias("label")), star.unionByName(pairs), EGO)


def cap_contributions(g: GraphTables, person, most: int) -> GraphTables:
    """At most `most` graphs of each person (a column expression over gid): those whose ids have the smallest digests.

    A walk over them takes `contribution=most`, as one person then moves a support by so much at the most.
    """
    digest = F.md5(F.col("gid").cast("string").cast("binary"))
    ids = g.vertices.select("gid").distinct().withColumn("n", F.row_number().over(Window.partitionBy(person).orderBy(digest, "gid")))
    kept = ids.where(F.col("n") <= most).select("gid")
    return GraphTables(g.vertices.join(kept, "gid", "left_semi"), g.edges.join(kept, "gid", "left_semi"), g.names)


WORKLOADS = {"click": click, "dense": dense, "profile": profile, "role": role_paths, "page": page_trees, "ego": ego_nets}
