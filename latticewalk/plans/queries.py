"""Queries of the engine over the given tables, and the same in SQL."""

from __future__ import annotations

import hashlib
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from latticewalk.functions import udfs
from latticewalk.functions.pattern import Pattern, PatternRules, enumerate_space, lattice_neighbors, parse_key, space_upper_bound
from latticewalk.operators import diagnostics, graphs, walk
from latticewalk.operators.store import shared_folder
from latticewalk.plans import experiments as ex
from latticewalk.plans import sql
from latticewalk.sources import builders, sinks
from latticewalk.streaming import sessions as streaming

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(oracle: str | None = None, name: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name or f.__name__] = f
        if oracle:
            ORACLES[name or f.__name__] = oracle
        return f

    return add


def each(names, oracle: Callable[[str], str | None], name: str):
    """One query for each of names, by a function of session, folder and name."""

    def add(f):
        for n in names:
            query(oracle(n), name.format(n))(lambda s, d, n=n: f(s, d, n))
        return f

    return add


CLICK_SQL, DENSE_SQL, HALF = sql.CLICK, sql.DENSE, sql.HALF
#: Patterns of up to two edges, which SQL can state for all workloads, and of up to three over three vertices.
SMALL = {w: PatternRules(ex.rules_of(w).labels, 3, 2) for w in sql.BASE}
WIDE = {w: PatternRules(ex.rules_of(w).labels, 3, 3) for w in sql.BASE}


def packed(s: SparkSession, d: str, name: str = "click") -> DataFrame:
    return ex.packed_of(s, d, name)


def halves(s: SparkSession, d: str, name: str = "click") -> DataFrame:
    return graphs.half_edges(packed(s, d, name))


def mined(s: SparkSession, d: str, name: str = "click", rules: PatternRules | None = None) -> DataFrame:
    return graphs.mine_supports(packed(s, d, name), rules or SMALL[name])


def supports(s: SparkSession, d: str, name: str = "click", rules: PatternRules | None = None) -> dict[str, int]:
    return ex.table_of(mined(s, d, name, rules))


# ---- graph databases ----


@each(sql.BASE, lambda n: f"with {sql.BASE[n]} select gid, vid, label from v", "build_{}_vertices")
def build_vertices(s, d, n):
    return builders.WORKLOADS[n](s, d).vertices


@each(sql.BASE, lambda n: f"with {sql.BASE[n]} select gid, src, dst from ed", "build_{}_edges")
def build_edges(s, d, n):
    return builders.WORKLOADS[n](s, d).edges


@each(
    sql.BASE,
    lambda n: f"""with {sql.BASE[n]}, c as (select gid, count(*) as n_vertices from v group by 1), k as (select gid, count(*) as n_edges from ed group by 1)
select n_vertices, coalesce(n_edges, 0) as n_edges, count(*) as n_graphs from c left join k using (gid) group by 1, 2""",
    "graph_sizes_{}",
)
def graph_sizes(s, d, n):
    sizes = packed(s, d, n).select(F.size("vlabel").cast("long").alias("n_vertices"), F.size("src").cast("long").alias("n_edges"))
    return sizes.groupBy("n_vertices", "n_edges").agg(F.count("*").alias("n_graphs"))


@each(
    sql.BASE,
    lambda n: f"with {sql.BASE[n]}, {HALF}, g as (select gid, v, lv, count(*) as degree from h group by 1, 2, 3) select lv as label, degree, count(*) as n from g group by 1, 2",
    "degree_histogram_{}",
)
def degree_histogram(s, d, n):
    degrees = halves(s, d, n).groupBy("gid", "v", F.col("v_label").alias("label")).agg(F.count("*").alias("degree"))
    return degrees.groupBy("label", "degree").agg(F.count("*").alias("n"))


@query("""select conv_id as gid, (k - 1)::int as src, k::int as dst
from (select conv_id, row_number() over (partition by conv_id order by turn, role, text) - 1 as k from conversations) where k > 0""")
def build_role_edges(s, d):
    return builders.role_paths(s, d).edges.selectExpr("gid", "cast(src as int) src", "cast(dst as int) dst")


@query()
def build_page_vertices(s, d):
    return builders.page_trees(s, d).vertices


@query()
def build_page_edges(s, d):
    return builders.page_trees(s, d).edges


@query(f"""with {CLICK_SQL}, p as (select gid, list(label order by vid) as vlabel from v group by gid), q as (select gid, count(*) as n_edges from ed group by gid)
select gid, array_to_string(vlabel, ',') as labels, n_edges from p join q using (gid)""")
def pack_graphs(s, d):
    return packed(s, d).select("gid", F.array_join(F.col("vlabel").cast("array<string>"), ",").alias("labels"), F.size("src").cast("long").alias("n_edges"))


@query(f"with {CLICK_SQL} select gid, src, dst from ed")
def unpack_edges(s, d):
    return graphs.unpack_edges(packed(s, d))


@query(f"with {CLICK_SQL} select gid, vid, label from v")
def src_graph_text(s, d):
    """Written as text in lines and read back."""
    place = shared_folder(s, "graph-text")
    sinks.write_graph_text(packed(s, d), place)
    return builders.read_graph_text(s, place).vertices


@query(f"with {CLICK_SQL} select gid, src, dst from ed")
def sink_packed(s, d):
    """Written as packed Parquet and read back."""
    place = shared_folder(s, "packed")
    sinks.write_packed(packed(s, d), place)
    return graphs.unpack_edges(s.read.parquet(place))


@query(f"""with {CLICK_SQL}, g as (select distinct gid from v), k as (select gid, row_number() over (partition by gid // {builders.SESSIONS} order by md5(gid::varchar), gid) as n from g)
select gid, count(*) as n_vertices from v where gid in (select gid from k where n <= 3) group by 1""")
def contribution_cap_click(s, d):
    """At most three sessions of each user, so that a user moves a support by three at the most."""
    g = builders.cap_contributions(builders.click(s, d), F.floor(F.col("gid") / builders.SESSIONS), 3)
    return g.vertices.groupBy("gid").agg(F.count("*").alias("n_vertices"))


@query(f"with {CLICK_SQL} select gid, label, count(*) as n from v group by 1, 2")
def label_histogram_map(s, d):
    return graphs.label_histogram(packed(s, d)).select("gid", F.explode("histogram").alias("label", "n")).withColumn("n", F.col("n").cast("long"))


@query(f"with {CLICK_SQL} select label, count(*) as n from v group by rollup (label)")
def label_rollup(s, d):
    return builders.click(s, d).vertices.rollup("label").agg(F.count("*").alias("n"))


@query(f"with {CLICK_SQL} select label, vid = 0 as root, count(*) as n from v group by cube (label, vid = 0)")
def label_cube(s, d):
    return builders.click(s, d).vertices.withColumn("root", F.col("vid") == 0).cube("label", "root").agg(F.count("*").alias("n"))


@query(f"with {CLICK_SQL} select count(distinct gid) as n from v where ('0x' || substr(md5(gid::varchar), 1, 8))::bigint % 100 < 40")
def fraction_md5(s, d):
    """A stable, nested share of the graphs, as the sweep of sizes takes it, by a hash that SQL has too."""
    h = F.conv(F.substring(F.md5(F.col("gid").cast("string").cast("binary")), 1, 8), 16, 10).cast("long")
    return builders.click(s, d).vertices.where(h % 100 < 40).agg(F.count_distinct("gid").alias("n"))


@query("select event_type, (json_extract(props, '$.k'))::int // 10 as k, count(*) as n from events group by 1, 2")
def src_props_label(s, d):
    e = builders.read(s, d, "events").select("event_type", F.get_json_object("props", "$.k").cast("int").alias("k"))
    return e.groupBy("event_type", F.floor(F.col("k") / 10).cast("int").alias("k")).agg(F.count("*").alias("n"))


# ---- lattice ----

SEEN_SQL = f"with {CLICK_SQL}, {sql.space(sql.SEEN)}, {sql.LATTICE}"
MINED_SQL = f"with {sql.table('click')}, {sql.space(5)}, {sql.LATTICE_2}"


def seen(s: SparkSession, d: str, edges: int = 3) -> PatternRules:
    """Patterns of up to three vertices and so many edges over the labels that occur in the click graphs."""
    labels = builders.click(s, d).vertices.select("label").where("label is not null").distinct().collect()
    return PatternRules(tuple(sorted(r.label for r in labels)), 3, edges)


@query(f"{SEEN_SQL} select k as pattern_key from se union select k from sp union select k from st")
def space_enumeration(s, d):
    """All patterns of the labels in the click graphs with up to three vertices and edges, whether or not they occur."""
    return s.createDataFrame([(k,) for k in enumerate_space(seen(s, d))], "pattern_key string")


@query(f"with {CLICK_SQL}, c as (select count(distinct label) as n from v) select (n * n + n * n * n * (3 + 1))::bigint as bound from c")
def space_bound(s, d):
    return s.createDataFrame([(space_upper_bound(seen(s, d)),)], "bound long")


@query(f"{SEEN_SQL} select * from lat")
def lattice_pairs(s, d):
    """A2-A5: every pattern of that space with its neighbours."""
    rules = seen(s, d)
    return graphs.neighbors_of(s.createDataFrame([(k,) for k in enumerate_space(rules)], "pattern_key string"), rules)


@query(f"{SEEN_SQL} select count(*) as one_way from lat a anti join lat b on a.pattern_key = b.near_key and a.near_key = b.pattern_key")
def lattice_reversible(s, d):
    """Pairs of neighbours that hold in one direction only."""
    pairs = lattice_pairs(s, d).select("pattern_key", "near_key")
    back = pairs.select(F.col("near_key").alias("pattern_key"), F.col("pattern_key").alias("near_key"))
    return pairs.join(back, ["pattern_key", "near_key"], "left_anti").agg(F.count("*").alias("one_way"))


@query("select * from (values (0, true), (5, true), (20, true)) t(removed, joined)")
def chain_conditions(s, d):
    """The space stays joined after the most supported patterns are removed one after the other."""
    rules, table = SMALL["click"], supports(s, d)
    lattice, rows = walk.PunchedLattice(rules), []
    for n, k in enumerate([*sorted(table, key=lambda k: (-table[k], k))[:20], ""]):
        if n in (0, 5, 20):
            rows.append((n, walk.joined(lattice, enumerate_space(rules))))
        lattice.remove(k)
    return s.createDataFrame(rows, "removed int, joined boolean")


@query(f"{MINED_SQL} select pattern_key, near_key, kind from lat semi join sup using (pattern_key)")
def neighbors_of(s, d):
    """A5: the neighbours of every pattern of the click graphs."""
    return graphs.neighbors_of(mined(s, d).select("pattern_key"), SMALL["click"])


@query(f"""{MINED_SQL}, k as (select pattern_key, row_number() over (order by support desc, pattern_key) as r from sup)
select near_key from lat join k using (pattern_key) where r = 1 except select near_key from lat join k using (pattern_key) where r = 2""")
def lattice_except(s, d):
    """The neighbours of the best pattern that the second best hasn't."""
    best = [r.pattern_key for r in graphs.top_k(mined(s, d), 2).collect()]
    near = lambda n: graphs.neighbors_of(s.createDataFrame([(k,) for k in best[n : n + 1]], "pattern_key string"), SMALL["click"]).select("near_key")
    return near(0).exceptAll(near(1))


@query(f"""with {CLICK_SQL}, {HALF}, q as (select distinct x.gid, {sql.path_key('x.lv', 'x.lw', 'y.lw')} as pattern_key
from h x join h y on x.gid = y.gid and x.v = y.v and x.w <> y.w and x.lw <= y.lw where x.lv <> 4) select pattern_key, count(*) as support from q group by 1""")
def filter_rules(s, d):
    """Only patterns of three vertices in which a view has one edge at the most."""
    return mined(s, d, rules=PatternRules(SMALL["click"].labels, 3, 2, 3, 2, degree_cap=((4, 1),)))


@query(f"with {CLICK_SQL}, {HALF}, {sql.PATH_KEYS} select * from pk")
def udf_pattern_key(s, d):
    """Keys of the paths in each graph, by the Arrow function."""
    h = halves(s, d)
    other = h.select("gid", "v", F.col("w").alias("w2"), F.col("w_label").alias("l2"))
    pairs = h.join(other, ["gid", "v"]).where("w <> w2 and w_label <= l2").select("gid", F.array("v_label", "w_label", "l2").alias("labels")).distinct()
    ends = [F.array(*map(F.lit, x)) for x in ((0, 0), (1, 2))]
    return pairs.select("gid", udfs.pattern_key("labels", *ends).alias("pattern_key"))


@query(f"with {CLICK_SQL}, {HALF}, {sql.PATH_KEYS} select gid from pk where pattern_key = '0,1,4|0-2,1-2'")
def udf_contains(s, d):
    return packed(s, d).where(udfs.contains_pattern("0,1,4|0-2,1-2")).select("gid")


# ---- matching and supports ----


@query(f"with {CLICK_SQL}, {HALF} select distinct lv as label_lo, lw as label_hi, gid from h where lv <= lw")
def edge_index(s, d):
    return graphs.edge_index(halves(s, d))


@each(sql.BASE, lambda n: f"with {sql.BASE[n]}, {HALF} select lv as label_lo, lw as label_hi, count(distinct gid) as support from h where lv <= lw group by 1, 2", "edge_support_{}")
def edge_support(s, d, n):
    return graphs.edge_supports(halves(s, d, n))


@each(sql.BASE, lambda n: f"with {sql.BASE[n]}, {HALF}, {sql.PATH_KEYS} select pattern_key, count(*) as support from pk group by 1", "support_path3_{}")
def support_path3(s, d, n):
    return mined(s, d, n).where("pattern_key like '%-%-%'")


@each(sql.BASE, lambda n: f"with {sql.table(n)} select * from sup", "mine_supports_{}")
def mine_supports(s, d, n):
    return mined(s, d, n)


@query(f"with {sql.table_3('dense')} select * from sup")
def mine_supports_dense_triangles(s, d):
    return mined(s, d, "dense", WIDE["dense"])


@query(f"""with {CLICK_SQL}, {HALF}, {sql.EDGE_KEYS}, vk as (select distinct gid, label || '|' as pattern_key from v)
select pattern_key, count(*) as support from (select * from vk union all select * from ek) group by 1""")
def mine_supports_click_vertices(s, d):
    """The space that begins at single vertices."""
    return mined(s, d, rules=PatternRules(SMALL["click"].labels, 2, 1, 1, 0))


@query()
def mine_supports_page(s, d):
    return graphs.mine_supports(builders.page_rows(builders.read(s, d, "pages")), ex.rules_of("page"))


@each(sql.BASE, lambda n: f"with {sql.table(n)} select * from sup order by support desc, pattern_key limit 15", "topk_patterns_{}")
def topk_patterns(s, d, n):
    return graphs.top_k(mined(s, d, n), 15)


TRIANGLE = Pattern((0, 1, 3), ((0, 1), (0, 2), (1, 2)))
STAR = Pattern((4, 0, 1, 3), ((0, 1), (0, 2), (0, 3)))
PATH4 = Pattern((0, 4, 4, 1), ((0, 1), (1, 2), (2, 3)))


@query(f"""with {DENSE_SQL}, {HALF} select a.gid from h a join h b on a.gid = b.gid and a.w = b.v join h c on c.gid = b.gid and c.v = b.w and c.w = a.v
where a.lv = 0 and b.lv = 1 and c.lv = 3 group by 1""")
def support_triangle_dense(s, d):
    return graphs.gid_set(packed(s, d, "dense"), TRIANGLE)


@query(f"""with {CLICK_SQL}, {HALF} select a.gid from h a join h b on a.gid = b.gid and a.v = b.v join h c on c.gid = b.gid and c.v = b.v
where a.lv = 4 and a.lw = 0 and b.lw = 1 and c.lw = 3 group by 1""")
def support_star4_click(s, d):
    return graphs.gid_set(packed(s, d), STAR)


@query(f"""with {CLICK_SQL}, {HALF} select a.gid from h a join h b on a.gid = b.gid and a.w = b.v join h c on c.gid = b.gid and c.v = b.w
where a.lv = 0 and b.lv = 4 and b.lw = 4 and c.lw = 1 and b.w <> a.v and c.w <> a.w and c.w <> a.v group by 1""")
def support_path4_click(s, d):
    return graphs.gid_set(packed(s, d), PATH4)


@query(f"""with {DENSE_SQL}, {HALF} select a.gid from h a join h b on a.gid = b.gid and a.w = b.v join h c on c.gid = b.gid and c.v = b.w
where a.lv = 0 and b.lv = 3 and c.lv = 1 and c.lw = 5 and b.w <> a.v and c.w <> a.w and c.w <> a.v group by 1""")
def support_rarest_first_dense(s, d):
    """B2 with the order of joins by the supports of the kinds of edges (the planner's table, which is small)."""
    own = packed(s, d, "dense")
    rare = {(r.label_lo, r.label_hi): r.support for r in graphs.edge_supports(graphs.half_edges(own)).collect()}
    p = Pattern((0, 3, 1, 5), ((0, 1), (1, 2), (2, 3)))
    return graphs.match_pattern(graphs.half_edges(graphs.holding_kinds(own, p)), p, rare).select("gid").distinct()


@query(f"with {CLICK_SQL}, {HALF} select distinct gid, 1::int as held from h where lv = 0 and lw = 4")
def membership_edge_click_view(s, d):
    """B7 and B8 together: the graphs tested are those that the kinds of edges leave."""
    left = graphs.holding_kinds(packed(s, d), parse_key("0,4|0-1"))
    return graphs.support_many(left, ["0,4|0-1"], also_graphs=True).select("gid", F.lit(1).alias("held"))


@query(f"with {CLICK_SQL}, {HALF} select count(distinct gid) as support from h where lv = 0 and lw = 4")
def bitmap_support(s, d):
    """Ids numbered densely, kept as bitmaps, counted by bits."""
    ids = graphs.gid_set(packed(s, d), Pattern((0, 4), ((0, 1),)))
    b = ids.groupBy(F.expr("bitmap_bucket_number(gid)").alias("b")).agg(F.expr("bitmap_construct_agg(bitmap_bit_position(gid))").alias("m"))
    return b.agg(F.sum(F.expr("bitmap_count(m)")).alias("support"))


@query(f"with {CLICK_SQL}, {HALF} select gid from h where lv = 0 and lw = 4 intersect select gid from h where lv = 1 and lw = 4")
def edgeset_intersect(s, d):
    i = graphs.edge_index(halves(s, d))
    return i.where("label_lo = 0 and label_hi = 4").select("gid").intersect(i.where("label_lo = 1 and label_hi = 4").select("gid"))


@query(f"""with {CLICK_SQL}, {HALF}, t(i, name) as (values {", ".join(f"({i}, '{n}')" for i, n in enumerate(builders.CLICK))})
select a.name as lo, b.name as hi, count(distinct gid) as support from h join t a on a.i = lv join t b on b.i = lw where lv <= lw group by 1, 2""")
def edge_support_named(s, d):
    """Names come from the declared labels, which are few."""
    names = F.broadcast(s.createDataFrame([*enumerate(builders.CLICK)], "i int, name string"))
    e = graphs.edge_supports(halves(s, d))
    return e.join(names.toDF("label_lo", "lo"), "label_lo").join(names.toDF("label_hi", "hi"), "label_hi").select("lo", "hi", "support")


@query(f"""with {sql.table('click')} select pattern_key, list_aggregate(list_transform(string_split(split_part(pattern_key, '|', 1), ','),
lambda x: [{', '.join(repr(n) for n in builders.CLICK)}][x::int + 1]), 'string_agg', ' ') as names from sup""")
def pattern_label_text(s, d):
    names = F.array(*map(F.lit, builders.CLICK))
    labels = F.split(F.split("pattern_key", r"\|")[0], ",")
    return mined(s, d).select("pattern_key", F.array_join(F.transform(labels, lambda x: F.element_at(names, x.cast("int") + 1)), " ").alias("names"))


@query()
def plan_stats_approx(s, d):
    """Sizes for planning only; supports are always exact."""
    h = halves(s, d).where("v_label <= w_label")
    return h.groupBy(F.col("v_label").alias("label_lo"), F.col("w_label").alias("label_hi")).agg(F.approx_count_distinct("gid").alias("about"))


# ---- miners ----

FREQUENT = f"with {sql.table('click')} select * from sup where support >= 200"
FREQUENT_3 = f"with {sql.table_3('dense')} select * from sup where support >= 150"


@query(FREQUENT)
def mine_levelwise_click(s, d):
    return graphs.mine_levelwise(packed(s, d), 200, SMALL["click"])


@query(FREQUENT)
def mine_growth_click(s, d):
    return graphs.mine_growth(packed(s, d), 200, SMALL["click"])


@query(FREQUENT_3)
def mine_levelwise_dense(s, d):
    return graphs.mine_levelwise(packed(s, d, "dense"), 150, WIDE["dense"])


@query(FREQUENT_3)
def mine_growth_dense(s, d):
    return graphs.mine_growth(packed(s, d, "dense"), 150, WIDE["dense"])


@query()
def mine_supports_click_whole(s, d):
    """Under the workload's own bounds, 4 nodes and 3 edges; the queries with SQL stop at 3 and 2."""
    return mined(s, d, "click", ex.rules_of("click"))


@query()
def mine_levelwise_click_whole(s, d):
    return graphs.mine_levelwise(packed(s, d), 200, ex.rules_of("click"))


@query()
def mine_growth_click_whole(s, d):
    return graphs.mine_growth(packed(s, d), 200, ex.rules_of("click"))


@query()
def topk_patterns_click_whole(s, d):
    return graphs.top_k(mined(s, d, "click", ex.rules_of("click")), 15)


BEST_15 = "(select support from sup order by support desc, pattern_key limit 15)"


@query(f"with {sql.table('click')} select * from sup where support >= (select min(support) from {BEST_15})")
def topk_ties_click(s, d):
    return graphs.top_k(mined(s, d), 15, ties=True)


@query(f"with {sql.table('click')} select min(support) as f from {BEST_15}")
def threshold_k15(s, d):
    return s.createDataFrame([(ex.threshold(supports(s, d), 15),)], "f long")


# ---- neighbour exploration ----


@query(f"""with {CLICK_SQL}, {HALF}, m as (select gid, v, w from h where lv = 0 and lw = 4),
f as (select m.gid, 0 as pos, h.lw as label from m join h on h.gid = m.gid and h.v = m.v and h.w <> m.w union all
      select m.gid, 1, h.lw from m join h on h.gid = m.gid and h.v = m.w and h.w <> m.v)
select pos::int as pos, label, count(distinct gid) as support from f group by 1, 2""")
def forward_supports_click_view(s, d):
    h = halves(s, d)
    found = graphs.forward_supports(graphs.match_pattern(h, Pattern((0, 4), ((0, 1),))), h, 2)
    return found.groupBy(F.col("at").alias("pos"), "label").agg(F.count_distinct("gid").alias("support"))


@query(f"""with {DENSE_SQL}, {HALF} select count(distinct a.gid) as support from h a join h b on a.gid = b.gid and a.w = b.v and b.w <> a.v
join h c on c.gid = a.gid and c.v = a.v and c.w = b.w where a.lv = 0 and a.lw = 2 and b.lw = 4""")
def back_supports_dense_path(s, d):
    h = halves(s, d, "dense")
    m = graphs.match_pattern(h, Pattern((0, 2, 4), ((0, 1), (1, 2))))
    return graphs.back_supports(m, h, (0, 2)).agg(F.count_distinct("gid").alias("support"))


@query(f"""with {DENSE_SQL}, {HALF}, ix as (select distinct gid, lv, lw from h),
b as (select a.gid from h a join h b on a.gid = b.gid and a.w = b.v and b.w <> a.v where a.lv = 1 and a.lw = 5 and b.lw = 2)
(select gid from ix where lv = 1 and lw = 5 intersect select gid from ix where lv = 2 and lw = 5) except select gid from b""")
def sub_candidates_dense(s, d):
    """The graphs with all kinds of edges of a path that don't hold it."""
    own, path = packed(s, d, "dense"), Pattern((1, 5, 2), ((0, 1), (1, 2))).key
    return graphs.sub_candidates(own, graphs.half_edges(own), path, path).select("gid")


#: A state with two smaller neighbours, a larger one that closes a triangle, and others; frequent or not by the threshold.
STATE, LOW, HIGH = "1,2,5|0-2,1-2", 100, 100_000
NEAR = lattice_neighbors("0,4|0-1", SMALL["click"])
NEAR_SQL = f"""with {sql.table('click')}, n(pattern_key) as (values {sql.values(x.key for x in NEAR)})
select n.pattern_key, coalesce(support, 0) >= 100 as frequent from n left join sup using (pattern_key)"""
DENSE_NEAR = f"with {sql.table_3('dense')}, {sql.space(6)}, {sql.LATTICE}"
STATE_SQL = f"""{DENSE_NEAR} select f, near_key as pattern_key, coalesce(support, 0) >= f as frequent
from lat left join sup on sup.pattern_key = near_key, (values ({LOW}), ({HIGH})) t(f) where lat.pattern_key = '{STATE}'"""

EXPLORERS = {
    "naive": lambda p, g, key, f, rules: graphs.explore_naive(p, key, f, rules),
    "monotone": lambda p, g, key, f, rules: graphs.explore_monotone(p, key, f, rules),
    "reuse": lambda p, g, key, f, rules: graphs.explore_reuse(p, key, f, rules),
    "reuse_joins": lambda p, g, key, f, rules: graphs.explore_reuse_joins(g, p, key, f, rules),
    "table": lambda p, g, key, f, rules: graphs.explore_table(ex.table_of(graphs.mine_supports(p, rules)), key, f, rules),
}


def classes(n: graphs.Neighborhood) -> list[tuple[str, bool]]:
    return [(k, True) for k in [*n.freq_sub, *n.freq_super]] + [(k, False) for k in n.infreq]


@each(EXPLORERS, lambda n: NEAR_SQL, "neighbors_{}")
def neighbors(s, d, n):
    g = builders.click(s, d)
    return s.createDataFrame(classes(EXPLORERS[n](graphs.pack(g), g, "0,4|0-1", 100, SMALL["click"])), "pattern_key string, frequent boolean")


@each(EXPLORERS, lambda n: STATE_SQL, "explore_dense_{}")
def explore_dense(s, d, n):
    """A path under a threshold that it meets and under one that it doesn't."""
    g, rows = builders.dense(s, d), []
    own = graphs.pack(g).persist()
    for f in (LOW, HIGH):
        rows += [(f, *x) for x in classes(EXPLORERS[n](own, g, STATE, f, WIDE["dense"]))]
    own.unpersist()
    return s.createDataFrame(rows, "f int, pattern_key string, frequent boolean")


@query(f"{DENSE_NEAR} select near_key as pattern_key, support from lat join sup on sup.pattern_key = near_key where lat.pattern_key = '{STATE}' and kind <> 'sub' union all select pattern_key, support from sup where pattern_key = '{STATE}'")
def grown_supports_dense(s, d):
    """C3c, C3d: a path and its larger neighbours that occur, from the path's own mappings."""
    return graphs.grown_supports(packed(s, d, "dense"), STATE, lattice_neighbors(STATE, WIDE["dense"])).where("support > 0")


@query(f"{DENSE_NEAR} select near_key as pattern_key, a.support - coalesce(b.support, 0) as n from lat join sup a on a.pattern_key = near_key left join sup b on b.pattern_key = lat.pattern_key where lat.pattern_key = '{STATE}' and kind = 'sub'")
def missed_supports_dense(s, d):
    """The graphs that hold an edge of the path and not the path."""
    return graphs.missed_supports(packed(s, d, "dense"), STATE, [x.key for x in lattice_neighbors(STATE, WIDE["dense"]) if x.kind == "sub"])


@query(f"""with {sql.table('click')}, n as (select count(distinct gid) as n from v), o as (select coalesce(sum(support), 0) >= 100 as fr from sup where pattern_key = '0,4|0-1')
select {len(NEAR) + 1} * n as naive_tests, case when fr then {len(NEAR) + 1} * n else n end as monotone_tests from n, o""")
def explorer_cost(s, d):
    """Of a pattern of one edge, which has no smaller neighbours: if it is frequent, the monotone rule saves nothing."""
    p = packed(s, d).persist()
    ways = (graphs.explore_naive, graphs.explore_monotone)
    rows = [tuple(explore(p, "0,4|0-1", 100, SMALL["click"]).counters["subgraph_tests"] for explore in ways)]
    p.unpersist()
    return s.createDataFrame(rows, "naive_tests long, monotone_tests long")


#: Graphs with both kinds of edges of the path (b), and with each that don't hold it: what reuse tests.
COST_SQL = f"""{DENSE_NEAR}, ix as (select distinct gid, lv, lw from h),
b as (select count(*) as b from (select gid from ix where lv = 1 and lw = 5 intersect select gid from ix where lv = 2 and lw = 5)),
n as (select count(distinct gid) as n from v), k as (select count(*) filter (kind = 'sub') as sub, count(*) filter (kind <> 'sub') as sup from lat where pattern_key = '{STATE}'),
o as (select coalesce(sum(support), 0) as own from sup where pattern_key = '{STATE}'),
e as (select coalesce(sum(support), 0) as ends from sup where pattern_key in ('1,5|0-1', '2,5|0-1'))"""


@query(f"""{COST_SQL} select f, n * (1 + sub + sup) as naive, case when own >= f then n * (1 + sup) else n * (1 + sub) end as monotone,
(2 * b + case when own >= f then 0 else ends - sub * own end)::bigint as reuse from b, n, k, o, e, (values ({LOW}), ({HIGH})) t(f)""")
def explorer_cost_dense(s, d):
    """Subgraph tests of each explorer on the path, from scratch (its own support counts a second time for reuse)."""
    own, rows = packed(s, d, "dense").persist(), []
    for f in (LOW, HIGH):
        rows.append((f, *(EXPLORERS[n](own, None, STATE, f, WIDE["dense"]).counters["subgraph_tests"] for n in ("naive", "monotone", "reuse"))))
    own.unpersist()
    return s.createDataFrame(rows, "f int, naive long, monotone long, reuse long")


# ---- scores, proposals, acceptance ----

SCORE_SQL = {"linear": "support::double", "plateau": "least(support, 100)::double", "steep": "case when support >= 100 then support::double else 0.5::double * (support - 1) end"}
#: The declared space of up to two edges with its supports, patterns of support 0 too.
SPACE_SQL = f"{sql.table('click')}, {sql.space(5)}, s as (select k as pattern_key, coalesce(support, 0) as support from (select k from se union select k from sp) left join sup on k = pattern_key)"


@each(SCORE_SQL, lambda n: f"with {sql.table('click')} select pattern_key, {SCORE_SQL[n]} as u from sup", "score_{}")
def score(s, d, n):
    u, _ = walk.SCORES[n](100)
    return s.createDataFrame([(k, u(x)) for k, x in supports(s, d).items()], "pattern_key string, u double")


@each(
    ("linear", "plateau"),
    lambda n: f"""with {SPACE_SQL}, u as (select pattern_key, {SCORE_SQL[n]} as u from s), w as (select pattern_key, exp(0.5::double * (u - (select max(u) from u)) / 30) as w from u)
select pattern_key, round(w / (select sum(w) from w), 9) as p from w""",
    "expmech_probs_{}",
)
def expmech_probs(s, d, n):
    """E2 over the declared space: patterns that don't occur have their share too."""
    law = walk.exponential_probs(enumerate_space(SMALL["click"]), supports(s, d), 0.5, 15, n, 100)
    return s.createDataFrame([(k, round(p, 9)) for k, p in law.items()], "pattern_key string, p double")


@query(f"""with {SPACE_SQL}, p as (select pattern_key, exp(0.02::double * (support - (select max(support) from s)) / 2) as w from s),
q as (select pattern_key, exp(0.02::double * (least(support, 100) - (select max(least(support, 100)) from s join se on k = pattern_key)) / 2) as w from s join se on k = pattern_key)
select round(sum(abs(coalesce(p.w / (select sum(w) from p), 0) - coalesce(q.w / (select sum(w) from q), 0))) / 2, 9) as tv from p full join q using (pattern_key)""")
def tv_distance(s, d):
    """E7 between the linear law over the space and the plateau's over its edges alone."""
    space, table = enumerate_space(SMALL["click"]), supports(s, d)
    p = walk.exponential_probs(space, table, 0.02, 1)
    q = walk.exponential_probs([k for k in space if k.count("-") == 1], table, 0.02, 1, "plateau", 100)
    return s.createDataFrame([(round(walk.tv_between(p, q), 9),)], "tv double")


@query(f"""with {sql.table('click')}, n(pattern_key) as (values {sql.values(x.key for x in NEAR)}), c as (select n.pattern_key, coalesce(support, 0) >= 100 as fr from n left join sup using (pattern_key)),
t as (select count(*) filter (fr) as a, count(*) filter (not fr) as b from c)
select pattern_key, round(case when fr then case when b = 0 then 1 else 0.9::double end / a else case when a = 0 then 1 else 0.1::double end / b end, 9) as q from c, t""")
def proposal_mass(s, d):
    n = graphs.explore_table(supports(s, d), "0,4|0-1", 100, SMALL["click"])
    a, b, c = walk.balanced_masses(len(n.freq_sub), len(n.freq_super), len(n.infreq), 0.9, 0.5)
    rows = [(k, round(m / len(ks), 9)) for m, ks in ((a, n.freq_sub), (b, n.freq_super), (c, n.infreq)) for k in ks]
    return s.createDataFrame(rows, "pattern_key string, q double")


@query(f"""with {sql.table('click')}, x as (select support as ux from sup where pattern_key = '0,4|0-1')
select pattern_key, round(least(1.0::double, exp(0.5::double * (support - ux) / 30) * (1 / 5.0::double) / (1 / 10.0::double)), 9) as alpha from sup, x""")
def mh_alpha(s, d):
    """D7 from one fixed state with |N(x)| = 10 and |N(y)| = 5 under uniform proposals."""
    table = supports(s, d)
    return s.createDataFrame([(k, round(walk.alpha(table["0,4|0-1"], x, 1 / 10, 1 / 5, 0.5, 15), 9)) for k, x in table.items()], "pattern_key string, alpha double")


@query(f"""{MINED_SQL}, n as (select pattern_key, support, count(*) as n from lat join sup using (pattern_key) group by 1, 2)
select lat.pattern_key, near_key, round(exp(least(0.0::double, 0.5::double * (b.support - a.support) / 30 + ln(a.n / b.n::double))), 9) as alpha
from lat join n a on a.pattern_key = lat.pattern_key join n b on b.pattern_key = near_key""")
def acceptance_example(s, d):
    """D7 between all patterns of the click graphs that are neighbours, under uniform proposals over N(x)."""
    table, rules = supports(s, d), SMALL["click"]
    near = {k: [n.key for n in lattice_neighbors(k, rules)] for k in table}
    rows = [(x, y, round(walk.alpha(table[x], table[y], 1 / len(near[x]), 1 / len(near[y]), 0.5, 15), 9)) for x in near for y in near[x] if y in table]
    return s.createDataFrame(rows, "pattern_key string, near_key string, alpha double")


@query(f"""with {SPACE_SQL}, {sql.LATTICE_2},
n as (select lat.pattern_key as x, near_key as y, a.support as sx, b.support as sy, case when b.support < 100 then 2 when kind = 'sub' then 0 else 1 end as class
      from lat join s a on a.pattern_key = lat.pattern_key join s b on b.pattern_key = near_key),
c as (select x, count(*) filter (class = 0) as n0, count(*) filter (class = 1) as n1, count(*) filter (class = 2) as n2 from n group by 1),
m as (select *, case when n0 = 0 then 0.0::double when n1 = 0 then 1 else 0.5 end as rho, case when n2 = 0 then 1.0::double else 0.9 end as eta from c),
q as (select n.*, case when n0 = 0 and n1 = 0 then 1.0::double / n2 when class = 0 then eta * rho / n0 when class = 1 then eta * (1 - rho) / n1 else (1 - eta) / n2 end as q from n join m using (x)),
p as (select a.x, a.y, a.q * least(1.0::double, exp(0.5::double * (a.sy - a.sx) / 30) * b.q / a.q) as p from q a join q b on a.x = b.y and a.y = b.x where a.q > 0)
select x as pattern_key, y as near_key, round(p, 9) as p from p where round(p, 9) > 0""")
def transition_rows(s, d):
    """The chance of each step of the chain with balanced proposals, over the declared space of up to two edges."""
    space = enumerate_space(SMALL["click"])
    walker = walk.Walker(walk.Materialized(supports(s, d)), walk.WalkConfig(SMALL["click"], k=15, f=100))
    matrix = walk.transition_matrix(walker, space)
    rows = [(space[i], space[j], round(float(matrix[i, j]), 9)) for i, j in zip(*matrix.nonzero()) if i != j]
    return s.createDataFrame([r for r in rows if r[2] > 0], "pattern_key string, near_key string, p double")


# ---- diagnostics, over the users' series of values ----


def series(s: SparkSession, d: str) -> DataFrame:
    by = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return builders.read(s, d, "events").select(F.col("user_id").alias("chain"), F.row_number().over(by).cast("long").alias("at"), "value")


@query("""with x as (select user_id, value, row_number() over (partition by user_id order by ts, event_id) as i, count(*) over (partition by user_id) as n from events),
a as (select user_id, avg(value) as m, var_samp(value) as v, count(*) as c from x where i <= n // 10 group by 1),
b as (select user_id, avg(value) as m, var_samp(value) as v from x where i > n - n // 2 group by 1)
select a.user_id, round((a.m - b.m) / sqrt(a.v + b.v), 9) as z from a join b using (user_id) where c > 1 and a.v + b.v > 0""")
def geweke_series(s, d):
    """Z of each user's series, first tenth against second half; below twenty values a tenth has no variance."""
    return diagnostics.geweke(series(s, d)).where("n >= 20").select(F.col("chain").alias("user_id"), F.round("z", 9).alias("z"))


@query("""with x as (select user_id, value, row_number() over (partition by user_id order by ts, event_id) as i from events),
c as (select user_id, i, sum(value) over w as s, sum(value * value) over w as q from x window w as (partition by user_id order by i rows unbounded preceding)),
t as (select *, greatest(1, i // 10) as a, greatest(1, i // 2) as b from c),
j as (select t.*, f.s as sa, f.q as qa, t.s - coalesce(l.s, 0) as sb, t.q - coalesce(l.q, 0) as qb from t join c f on f.user_id = t.user_id and f.i = t.a left join c l on l.user_id = t.user_id and l.i = t.i - t.b),
v as (select user_id, i, sa / a - sb / b as d, case when a > 1 then greatest(0, (qa - sa * sa / a) / (a - 1)) else 0 end + case when b > 1 then greatest(0, (qb - sb * sb / b) / (b - 1)) else 0 end as v from j),
k as (select user_id, i, (i >= 10 and case when v <= 1e-12 then abs(d) < 1e-12 else abs(d / sqrt(v)) <= 1 end)::int as ok from v)
select user_id, i as at, min(ok) over w = 1 and count(*) over w = 20 as converged from k window w as (partition by user_id order by i rows 19 preceding)""")
def converged_flag(s, d):
    """Whether |Z| has been at most 1 for twenty steps, at each step of each user's series."""
    return diagnostics.converged(series(s, d)).withColumnRenamed("chain", "user_id")


@query("""with c as (select user_id, count(value) as n, avg(value) as m, var_samp(value) as v from events group by 1 having count(value) > 1),
t as (select avg(n) as n, sum(n * m) / sum(n)::double as mean, sum((n - 1) * v) / sum(n - 1)::double as w from c),
b as (select sum(c.n * (c.m - t.mean) * (c.m - t.mean)) / (count(*) - 1) as b from c, t)
select round(sqrt(((n - 1) / n * w + b / n) / w), 9) as r_hat from t, b""")
def gelman_rubin(s, d):
    """D14 over the whole series of all users, which needn't be of one length."""
    return diagnostics.scale_reduction(series(s, d)).select(F.round("r_hat", 9).alias("r_hat"))


# ---- mechanisms and bounds ----


def hashed_noise(key: str, salt: int, scale: float) -> float:
    """Noise by the inverse distribution from a hash, as tests need it repeatable."""
    u = (int(hashlib.md5(f"{key}:{salt}".encode()).hexdigest()[:13], 16) + 0.5) / 2**52 - 0.5
    return walk.laplace_quantile(u, scale)


def noise_sql(salt: int, scale: str) -> str:
    u = f"((('0x' || substr(md5(pattern_key || ':{salt}'), 1, 13))::bigint + 0.5::double) / 4503599627370496::double - 0.5::double)"
    return f"- {scale} * sign({u}) * ln(1 - 2 * abs({u}))"


@query(f"with {sql.table('click')}, k as (select * from sup order by support desc, pattern_key limit 15) select pattern_key, round(support {noise_sql(3, '30')}, 6) as noisy from k")
def laplace_md5(s, d):
    """Noise of scale k / eps2 = 30 on the supports of the best patterns."""
    best = graphs.top_k(mined(s, d), 15).collect()
    return s.createDataFrame([(r.pattern_key, round(r.support + hashed_noise(r.pattern_key, 3, 30.0), 6)) for r in best], "pattern_key string, noisy double")


@query(f"with {SPACE_SQL}, z as (select pattern_key, support {noise_sql(5, '(90 / 0.5::double)')} as noisy from s) select pattern_key, round(noisy, 6) as noisy from z order by z.noisy desc, pattern_key limit 15")
def laplace_all_md5(s, d):
    """the direct way, noise of scale |space| / eps on every pattern of the space, then the best 15."""
    out = walk.laplace_all(enumerate_space(SMALL["click"]), supports(s, d), 15, 0.5, lambda k, scale: hashed_noise(k, 5, scale))
    return s.createDataFrame([(k, round(x, 6)) for k, x in out], "pattern_key string, noisy double")


@query(f"""{SEEN_SQL}, m as (select (select count(*) from se) as e, (select count(*) from sp) as p, (select count(*) from st) as t),
n as (select unnest([e, e + p, e + p + t])::int as m from m) select m, round(2 * 15 / 0.5::double * (ln(15 / 0.05::double) + ln(m)), 6) as beta from n where m > 0""")
def utility_beta(s, d):
    """E11 for the spaces of up to one, two and three edges over the labels in the click graphs."""
    sizes = [len(enumerate_space(replace(rules, max_edges=e))) for rules in [seen(s, d)] for e in (1, 2, 3)]
    return s.createDataFrame([(m, round(walk.utility_beta(15, 0.5, 0.05, m), 6)) for m in sizes if m], "m int, beta double")


@query(f"""with {sql.table('click')}, k as (select * from sup order by support desc, pattern_key limit 15)
select pattern_key, round(support - 15 / 0.5::double * ln(1 / 0.05::double), 6) as one, round(support - 15 / 0.5::double * ln(15 / 0.05::double), 6) as all_k from k""")
def noise_beta(s, d):
    """What the noisy supports of the best patterns are above, each by itself and all at once."""
    one, every = walk.noise_beta(15, 0.5, 0.05), walk.noise_beta(15, 0.5, 0.05, True)
    best = graphs.top_k(mined(s, d), 15)
    return best.select("pattern_key", F.round(F.col("support") - F.lit(one), 6).alias("one"), F.round(F.col("support") - F.lit(every), 6).alias("all_k"))


@query(f"""with {sql.table('click')}, k as (select unnest([5, 15, 30]) as k), w as (select k, exp(0.5::double * (support - (select max(support) from sup)) / (2 * k)) as w from sup, k),
t as (select k, w, sum(w) over (partition by k) as s, count(*) over (partition by k) as n from w), d as (select k, sum(abs(w / s - 1 / n::double)) / 2 as theta from t group by 1)
select k, round(theta, 9) as theta, round(theta * (1 + exp(0.5::double / k)), 9) as delta from d""")
def delta_for(s, d):
    """E6 where theta is how far the law over the click patterns is from the even one, as for a chain that has forgotten supports."""
    table, rows = supports(s, d), []
    for k in (5, 15, 30) if table else ():
        theta = walk.tv_distance(walk.exponential_law([*table.values()], 0.5, k), [1 / len(table)] * len(table))
        rows.append((k, round(theta, 9), round(walk.delta_for(theta, 0.5, k), 9)))
    return s.createDataFrame(rows, "k int, theta double, delta double")


@query(f"""with {sql.table('click')}, c as (select count(*) as k from sup where support >= 100)
select 0.75::double as eps, 0.0::double as delta_at_law, case when k = 0 then 0.0::double else round(least(1.0::double, k * 0.0001::double * (1 + exp(0.5::double / k))), 12) end as delta,
  case when k = 0 then 2 else 3 end as phases from c""")
def composition_ledger(s, d):
    """What a release of all frequent click patterns spends, at the law and with a bound on the distance of each chain from it."""
    ledger, k = walk.BudgetLedger(), mined(s, d).where("support >= 100").count()
    ledger.spend("sampling", 0.5)
    ledger.spend("supports", 0.25)
    if k:
        ledger.away(k, 0.5, 0.0001)
    return s.createDataFrame([(ledger.total[0], ledger.ideal[1], round(ledger.total[1], 12), len(ledger.rows))], "eps double, delta_at_law double, delta double, phases int")


# ---- measures ----

OUT = ("0,4|0-1", "3,4|0-1", "1,4|0-1", "0,0|0-1", "2,2|0-1")
OUT_SQL = f"""with {sql.table('click')}, o(pattern_key) as (values {sql.values(OUT)}), best as (select * from sup order by support desc, pattern_key limit 5),
t as (select (select count(*) from o semi join best using (pattern_key)) / 5.0::double as precision_strict,
  (select count(*) from o join sup using (pattern_key) where support >= (select min(support) from best)) / 5.0::double as precision_ties,
  ((select sum(support) from best) - (select sum(support) from o join sup using (pattern_key))) / 5.0::double / (select min(support) from best) as rse)"""


def measures(s: SparkSession, d: str) -> dict[str, float]:
    return walk.metrics([*OUT], supports(s, d), 5)


@query(f"{OUT_SQL} select precision_strict, 1 - precision_strict as false_negative_rate from t")
def precision_strict(s, d):
    m = measures(s, d)
    return s.createDataFrame([(m["precision"], m["false_negative_rate"])], "precision_strict double, false_negative_rate double")


@query(f"{OUT_SQL} select precision_ties from t")
def precision_ties(s, d):
    return s.createDataFrame([(measures(s, d)["precision_ties"],)], "precision_ties double")


@query(f"{OUT_SQL} select round(rse, 9) as rse, round(1 - rse, 9) as support_accuracy from t")
def support_accuracy(s, d):
    m = measures(s, d)
    return s.createDataFrame([(round(m["rse"], 9), round(m["support_accuracy"], 9))], "rse double, support_accuracy double")


@query(f"""{OUT_SQL}, f as (select min(support) as f from best), b(beta) as (values (1.0::double), (100.0::double), (5000.0::double))
select beta, (select bool_and(coalesce(support, 0) > f - beta) from o left join sup using (pattern_key)) as sound,
  not exists (select 1 from sup where support > f + beta and pattern_key not in (select pattern_key from o)) as complete from b, f""")
def soundness_completeness(s, d):
    """E11, E12 of a fixed list of outputs, at some distances from the threshold."""
    table = supports(s, d)
    f = ex.threshold(table, 5)
    return s.createDataFrame([(b, walk.sound([*OUT], table, f, b), walk.complete([*OUT], table, f, b)) for b in (1.0, 100.0, 5000.0)], "beta double, sound boolean, complete boolean")


@query(f"with {sql.table('click')}, n as (select count(distinct gid) as n from v) select pattern_key, round(support / n::double, 9) as frequency from (select * from sup order by support desc, pattern_key limit 15), n")
def frequency_form(s, d):
    """Supports as shares of the number of graphs."""
    best = {r.pattern_key: r.support for r in graphs.top_k(mined(s, d), 15).collect()}
    shares = walk.frequency_form(best, packed(s, d).count())
    return s.createDataFrame([(k, round(x, 9)) for k, x in shares.items()], "pattern_key string, frequency double")


@query(f"""with {sql.table('click')}, r as (select 'support' as metric, 'click' as workload, (len(pattern_key) - len(replace(pattern_key, '-', '')))::varchar as value, support::double as measure from sup)
select metric, workload, value, count(*) as n, round(avg(measure), 9) as mean from r group by rollup (metric, workload, value) having metric is not null""")
def summary_rollup(s, d):
    """The rollup of results, here of supports by number of edges."""
    edges = F.expr("cast(length(pattern_key) - length(replace(pattern_key, '-', '')) as string)")
    rows = mined(s, d).select(F.lit("click").alias("workload"), edges.alias("value"), F.lit("support").alias("metric"), F.col("support").cast("double").alias("measure"))
    return ex.summary_rollup(rows)


# ---- streams ----


@query("select date_trunc('day', ts) as began, event_type, count(*) as n from events group by 1, 2")
def window_event_counts(s, d):
    """The batch twin of the tumbling monitor."""
    return streaming.event_counts(builders.read(s, d, "events")).select(F.col("began").cast("timestamp_ntz").alias("began"), "event_type", "n")


@query("select time_bucket(interval 6 hours, ts) - k * interval 6 hours as began, event_type, count(*) as n from events, (values (0), (1), (2), (3)) t(k) group by 1, 2")
def window_event_counts_sliding(s, d):
    """The batch twin of the sliding monitor: a day, every six hours."""
    return streaming.event_counts(builders.read(s, d, "events"), "1 day", "6 hours").select(F.col("began").cast("timestamp_ntz").alias("began"), "event_type", "n")


@query(f"with {CLICK_SQL} select count(*) as n_sessions, sum(c)::bigint as n_events from (select user_id, sess, count(*) as c from e1 group by 1, 2)")
def session_totals(s, d):
    """The batch twin of the session stream, single events included."""
    return streaming.stream_sessions(builders.read(s, d, "events")).agg(F.count("*").alias("n_sessions"), F.sum("n").alias("n_events"))


@query("""with e as (select ts, max(ts) over (order by event_id rows between unbounded preceding and 1 preceding) as newest from events)
select ts::date::varchar as day, count(*) as n, sum(coalesce((ts < newest - interval 1 hour)::int, 0))::bigint as late from e group by 1""")
def late_events(s, d):
    """Events that a stream with a delay of an hour may drop, if they come in the order of their ids."""
    return streaming.late_events(builders.read(s, d, "events"))


def stream_of(s: SparkSession, d: str) -> DataFrame:
    schema = builders.read(s, d, "events").schema
    return s.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(d)


@query()
def stream_sessions(s, d):
    """The stream itself, over the events as they lie, up to the watermark."""
    return streaming.run_to_table(streaming.stream_sessions(stream_of(s, d)), shared_folder(s, "stream-sessions"))


@query()
def stream_click_graphs(s, d):
    """Session trees built by the stateful operator, up to the watermark."""
    return streaming.run_to_table(streaming.stream_click_graphs(stream_of(s, d)), shared_folder(s, "stream-click-graphs"))


# ---- releases and experiments ----

for _name in [*sql.BASE, "page"]:
    query(name=f"private_walk_{_name}")(lambda s, d, n=_name: ex.private_walk(s, d, n, 15))
for _name in ("vertices", "bridged"):
    query(name=f"private_walk_click_{_name}")(lambda s, d, n=_name: ex.private_walk(s, d, "click", 15, lattice=n))

PERCENTS, EPS, KS, SHARES = [10, 40, 70, 100], [0.1, 0.2, 0.3, 0.4, 0.5, 0.7, 1.0], [5, 10, 15, 20, 25, 30], [0.4, 0.5, 0.6, 0.7, 0.8, 0.9]
EXPERIMENTS: dict[str, Query] = {
    "laplace_release_rows": lambda s, d: ex.private_walk(s, d, "click", 15, 0.5),
    "private_walk_on_data": lambda s, d: ex.private_walk(s, d, "click", 2, explorer="reuse"),
    "walk_by_explorer": lambda s, d: ex.walk_by_explorer(s, d),
    "walk_costs": lambda s, d: ex.walk_costs(s, d),
    "walk_costs_click": lambda s, d: ex.walk_costs(s, d, workloads=("click",), steps=4),
    "explorer_comparison": lambda s, d: ex.explorer_comparison(s, d),
    "time_by_size": lambda s, d: ex.time_by_size(s, d),
    "time_scaling": lambda s, d: ex.scaling_fit(ex.time_by_size(s, d)),
    "sweep_size": lambda s, d: ex.sweep(s, d, {"lattice": ["plain", "vertices"], "percent": PERCENTS}),
    "sweep_eps": lambda s, d: ex.sweep(s, d, {"lattice": ["plain", "vertices"], "eps": EPS}),
    "sweep_k": lambda s, d: ex.sweep(s, d, {"lattice": ["plain", "vertices"], "k": KS}),
    "sweep_score": lambda s, d: ex.sweep(s, d, {"lattice": ["vertices"], "percent": [10, 40, 100], "score": ["linear", "plateau", "steep"]}, ("click", "dense")),
    "sweep_eta": lambda s, d: ex.sweep(s, d, {"lattice": ["plain", "vertices"], "eta": SHARES}),
    "sweep_rho": lambda s, d: ex.sweep(s, d, {"lattice": ["plain", "vertices"], "rho": SHARES}),
    "sweep_lattice": lambda s, d: ex.sweep(s, d, {"lattice": [*ex.LATTICES]}),
    "exact_vs_walk": lambda s, d: ex.exact_vs_walk(s, d),
    "exact_vs_walk_distance": lambda s, d: ex.exact_vs_walk_distance(s, d),
    "tv_after_steps": lambda s, d: ex.tv_after_steps(s, d),
    "measured_ledger": lambda s, d: ex.measured_ledger(s, d),
    "convergence_traces": lambda s, d: ex.convergence_traces(s, d),
}
for _name, _run in EXPERIMENTS.items():
    query(name=_name)(_run)
