"""Graph databases, matching, supports and neighbour exploration as DataFrame plans.

Two layouts: relational (joins on gid and vertex) and packed (a nested row per graph, matched row by row in
Arrow batches without any shuffle). Supports are sums over graphs, so one scan with map-side counts gives all
of them (B5), and everything after that works on the small table of supports.
"""

from __future__ import annotations

import time
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from latticewalk.functions.pattern import (
    Neighbor,
    Pattern,
    PatternRules,
    Recent,
    Step,
    adjacency,
    clean,
    contains,
    each_mapping,
    is_minimal,
    kinds_of,
    lattice_neighbors,
    parse_key,
    pattern_of,
    rightmost_steps,
    sub_pattern_keys,
    within,
)
from latticewalk.sources.builders import GraphTables


def pack(g: GraphTables) -> DataFrame:
    """gid, vlabel, src, dst: one row per graph; vertices in order of vid, which counts from 0 without gaps.

    A vertex without a label has -1, which no pattern holds. One graph is one person's data and bounded.
    """
    label = F.coalesce("label", F.lit(-1)).alias("label")
    v = g.vertices.groupBy("gid").agg(F.transform(F.sort_array(F.collect_list(F.struct("vid", label))), lambda x: x["label"]).alias("vlabel"))
    e = g.edges.groupBy("gid").agg(F.sort_array(F.collect_list(F.struct("src", "dst"))).alias("e"))
    ends = [F.coalesce(F.col(f"e.{c}"), F.array().cast("array<int>")).alias(c) for c in ("src", "dst")]
    return v.join(e, "gid", "left").select("gid", "vlabel", *ends)


def unpack_edges(packed: DataFrame) -> DataFrame:
    return packed.select("gid", F.explode(F.arrays_zip("src", "dst")).alias("e")).select("gid", "e.src", "e.dst")


def half_edges(g: GraphTables | DataFrame) -> DataFrame:
    """gid, v, w, v_label, w_label: each edge from both ends. Labels are read within the packed row, without a join."""
    packed = pack(g) if isinstance(g, GraphTables) else g
    e = packed.select("gid", "vlabel", F.explode(F.arrays_zip("src", "dst")).alias("e"))
    e = e.selectExpr("gid", "e.src s", "e.dst d", "get(vlabel, e.src) a", "get(vlabel, e.dst) b").where("a >= 0 and b >= 0")
    return e.selectExpr("gid", "inline(array(struct(s v, d w, a v_label, b w_label), struct(d v, s w, b v_label, a w_label)))")


def edge_index(h: DataFrame) -> DataFrame:
    """B4. label_lo, label_hi, gid: the graphs of each kind of edge."""
    return h.where("v_label <= w_label").select(F.col("v_label").alias("label_lo"), F.col("w_label").alias("label_hi"), "gid").distinct()


def edge_supports(h: DataFrame) -> DataFrame:
    return edge_index(h).groupBy("label_lo", "label_hi").agg(F.count("*").alias("support"))


def match_pattern(h: DataFrame, p: Pattern, rare: dict[tuple[int, int], int] | None = None) -> DataFrame:
    """B2. gid, m0, m1, ...: a join of half edges for each edge, on the graph and the bound vertices.

    rare: supports of kinds of edges; the join then begins with the rarest, and goes on with the rarest that hangs on it.
    """
    seldom = lambda e: (rare or {}).get(tuple(sorted((p.labels[e[0]], p.labels[e[1]]))), 0)
    order = [min(p.edges, key=seldom)]
    while len(order) < len(p.edges):
        order.append(min((e for e in p.edges if e not in order and any(v in f for f in order for v in e)), key=seldom))
    u, v = order[0]
    out, bound = h.where(f"v_label = {p.labels[u]} and w_label = {p.labels[v]}").select("gid", F.col("v").alias(f"m{u}"), F.col("w").alias(f"m{v}")), [u, v]
    for u, v in order[1:]:
        if u in bound and v in bound:
            out = out.join(h.select("gid", F.col("v").alias(f"m{u}"), F.col("w").alias(f"m{v}")), ["gid", f"m{u}", f"m{v}"])
            continue
        a, b = (u, v) if u in bound else (v, u)
        step = h.where(f"v_label = {p.labels[a]} and w_label = {p.labels[b]}").select("gid", F.col("v").alias(f"m{a}"), F.col("w").alias(f"m{b}"))
        out = out.join(step, ["gid", f"m{a}"]).where(" and ".join(f"m{b} <> m{c}" for c in bound))
        bound.append(b)
    return out.select("gid", *(f"m{i}" for i in range(len(p.labels))))


def holding_kinds(packed: DataFrame, p: Pattern) -> DataFrame:
    """B8. The graphs that hold all kinds of edges of p, by a test within the packed row."""
    ends = "(get(vlabel, e.src) = {} and get(vlabel, e.dst) = {})"
    for lo, hi in sorted(kinds_of(p)):
        packed = packed.where(f"exists(arrays_zip(src, dst), e -> {ends.format(lo, hi)} or {ends.format(hi, lo)})")
    return packed


def gid_set(packed: DataFrame, p: Pattern) -> DataFrame:
    """B3, B8. The graphs that hold p, by joins over those that hold all its kinds of edges."""
    return match_pattern(half_edges(holding_kinds(packed, p)), p).select("gid").distinct()


def arrays(batches: Iterable[pd.DataFrame], *more: str) -> Iterator[list[tuple]]:
    """Rows (labels, src, dst, and the columns named) of packed batches, as Python numbers."""
    for batch in batches:
        rest = [batch[c] for c in more]
        yield [(clean(a.tolist()), b.tolist(), c.tolist(), *r) for a, b, c, *r in zip(batch["vlabel"], batch["src"], batch["dst"], *rest, strict=True)]


def keyed(counts: dict, **columns) -> pd.DataFrame:
    """A frame of counts by key with its types stated, as an empty one has none."""
    return pd.DataFrame({"pattern_key": pd.Series(list(counts), dtype="str"), **{c: pd.Series(v, dtype="int64") for c, v in columns.items()}})


def support_many(packed: DataFrame, keys: list[str], also_graphs: bool = False) -> DataFrame:
    """B7. key, support of many patterns in one pass over packed rows; patterns held by no graph are left out."""

    def test(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        patterns = [(k, parse_key(k)) for k in keys]
        for rows in arrays(batches, "gid"):
            hits = []
            for labels, src, dst, gid in rows:
                near = adjacency(len(labels), src, dst)
                hits += [(gid, k) for k, p in patterns if contains(labels, near, p)]
            if hits:
                yield pd.DataFrame(hits, columns=["gid", "pattern_key"])

    hits = packed.select("gid", "vlabel", "src", "dst").mapInPandas(test, "gid long, pattern_key string")
    return hits if also_graphs else hits.groupBy("pattern_key").agg(F.count("*").alias("support"))


def mine_supports(packed: DataFrame, rules: PatternRules) -> DataFrame:
    """B5. pattern_key, support of every pattern within the rules that occurs, in one scan; others have support 0."""

    def emit(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for rows in arrays(batches):
            keys: dict[str, int] = {}
            for graph in rows:
                for k in sub_pattern_keys(*graph, rules.max_edges, rules.max_nodes, rules.min_edges == 0):
                    keys[k] = keys.get(k, 0) + 1
            keys = {k: n for k, n in keys.items() if rules.allows(parse_key(k))}
            if keys:
                yield keyed(keys, n=list(keys.values()))

    return packed.select("vlabel", "src", "dst").mapInPandas(emit, "pattern_key string, n long").groupBy("pattern_key").agg(F.sum("n").alias("support"))


def mine_levelwise(packed: DataFrame, threshold: int, rules: PatternRules) -> DataFrame:
    """F1. Level by level: candidates one edge larger than frequent ones, kept if all their sub-patterns are frequent.

    Each graph carries which candidates of the last level it holds: a candidate is tested only on graphs that hold all
    its sub-patterns, and a graph that holds none is dropped. Only frequent patterns, which the threshold bounds in
    number, come to the driver.
    """
    spark, columns = packed.sparkSession, ["gid", "vlabel", "src", "dst"]
    wide = replace(rules, min_nodes=2, min_edges=1)
    ones = [Pattern((a, b), ((0, 1),)).key for a in rules.labels for b in rules.labels if a <= b]
    level: list[tuple[str, tuple[int, ...]]] = [(k, ()) for k in ones if wide.allows(parse_key(k))]
    out, state, last = [], packed.select(*columns, F.array().cast("array<int>").alias("held")), None
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in state.schema)

    def tested(level: list) -> DataFrame:
        def test(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            patterns = [(i, parse_key(k), subs) for i, (k, subs) in enumerate(level)]
            for rows in arrays(batches, "gid", "held"):
                kept = []
                for labels, src, dst, gid, before in rows:
                    near, before = adjacency(len(labels), src, dst), set(before.tolist())
                    held = [i for i, p, subs in patterns if before.issuperset(subs) and contains(labels, near, p)]
                    if held:
                        kept.append((gid, labels, src, dst, held))
                if kept:
                    yield pd.DataFrame(kept, columns=[*columns, "held"])

        return state.mapInPandas(test, schema)

    while level:
        state = tested(level).persist()
        counts = state.select(F.explode("held").alias("at")).groupBy("at").agg(F.count("*").alias("n")).where(F.col("n") >= threshold)
        found = {level[r["at"]][0]: (r["at"], r.n) for r in counts.collect()}
        if last is not None:
            last.unpersist()
        last = state
        out += [(k, n) for k, (_, n) in found.items()]
        grown = {n.key for k in found for n in lattice_neighbors(k, wide) if n.kind.startswith("super")}
        subs_of = {k: [n.key for n in lattice_neighbors(k, wide) if n.kind == "sub"] for k in sorted(grown)}
        level = [(k, tuple(found[s][0] for s in subs)) for k, subs in subs_of.items() if all(s in found for s in subs)]
    if last is not None:
        last.unpersist()
    return spark.createDataFrame([x for x in out if rules.allows(parse_key(x[0]))], "pattern_key string, support long")


def code_text(code: tuple[Step, ...]) -> str:
    return ";".join(",".join(map(str, t)) for t in code)


def read_code(text: str) -> tuple[Step, ...]:
    return tuple(tuple(map(int, t.split(","))) for t in text.split(";"))


def mine_growth(packed: DataFrame, threshold: int, rules: PatternRules) -> DataFrame:
    """F2, B6. Growth along minimal depth-first codes: a row is a graph with one frequent code and all its images in it.

    Each level grows every row by the steps of its rightmost path, one row a new code, and counts codes. A minimal code
    has one prefix only, which is minimal too, so no (graph, code) arises twice, supports are counts of rows, and only
    codes are shuffled. Codes that aren't minimal are dropped where they arise, infrequent ones before they grow. The
    patterns of a graph with many of them lie in many rows, which Spark deals to tasks. Frequent codes, which the
    threshold bounds in number, come to the driver.
    """
    spark, columns = packed.sparkSession, ["gid", "vlabel", "src", "dst"]
    names = [*columns, "code", "images"]
    wide, public = replace(rules, min_nodes=2, min_edges=1), set(rules.labels)
    schema = ", ".join(f"{c} {packed.schema[c].dataType.simpleString()}" for c in columns) + ", code string, images binary"

    def frames(rows: Iterator[tuple]) -> Iterator[pd.DataFrame]:
        some = []
        for row in rows:
            some.append(row)
            if len(some) >= 2000:
                yield pd.DataFrame(some, columns=names)
                some = []
        if some:
            yield pd.DataFrame(some, columns=names)

    def found(graph: tuple, images: dict[tuple, list]) -> Iterator[tuple]:
        for code, own in images.items():
            if is_minimal(code) and wide.allows(pattern_of(code)):
                yield (*graph, code_text(code), np.array(own, np.int32).tobytes())

    def first(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def rows() -> Iterator[tuple]:
            for batch in arrays(batches, "gid"):
                for labels, src, dst, gid in batch:
                    images: dict[tuple, list] = {}
                    for u, v in {*zip(src, dst), *zip(dst, src)}:
                        if labels[u] in public and labels[v] in public and labels[u] <= labels[v]:
                            images.setdefault(((0, 1, labels[u], labels[v]),), []).append((u, v))
                    yield from found((gid, labels, src, dst), images)

        yield from frames(rows())

    def grown(rows: DataFrame, frequent: set[str]) -> DataFrame:
        def grow(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            def out() -> Iterator[tuple]:
                for batch in arrays(batches, "gid", "code", "images"):
                    for labels, src, dst, gid, text, raw in batch:
                        if text not in frequent:
                            continue
                        code, near, images = read_code(text), adjacency(len(labels), src, dst), {}
                        width = 1 + max(max(t[:2]) for t in code)
                        for image in map(tuple, np.frombuffer(raw, np.int32).reshape(-1, width).tolist()):
                            for step, w in rightmost_steps(code, image, labels, near):
                                if w < 0 or (labels[w] in public and width < rules.max_nodes):
                                    images.setdefault((*code, step), []).append((*image, w) if w >= 0 else image)
                        yield from found((gid, labels, src, dst), images)

            yield from frames(out())

        return rows.mapInPandas(grow, schema)

    out, rows, size = [], packed.select(*columns).mapInPandas(first, schema).persist(), 1
    while True:
        counts = rows.groupBy("code").agg(F.count("*").alias("n")).where(F.col("n") >= threshold).collect()
        out += [(pattern_of(read_code(r.code)).key, r.n) for r in counts]
        if not counts or size >= rules.max_edges:
            rows.unpersist()
            break
        last, rows, size = rows, grown(rows, {r.code for r in counts}).persist(), size + 1
        rows.count()
        last.unpersist()
    return spark.createDataFrame([x for x in out if rules.allows(parse_key(x[0]))], "pattern_key string, support long")


def top_k(supports: DataFrame, k: int, ties: bool = False) -> DataFrame:
    """F3. The k best by support, ties by key; with ties, all at least as good as the k-th."""
    best = supports.orderBy(F.desc("support"), "pattern_key").limit(k)
    return supports.join(best.agg(F.min("support").alias("least")), F.col("support") >= F.col("least")).drop("least") if ties else best


@dataclass
class Neighborhood:
    support: int
    freq_sub: list[str]
    freq_super: list[str]
    infreq: list[str]
    counters: dict[str, float] = field(default_factory=dict)


def _split(x_support: int, neighbors: tuple[Neighbor, ...], frequent: dict[str, bool], counters: dict) -> Neighborhood:
    subs = [n.key for n in neighbors if n.kind == "sub" and frequent[n.key]]
    supers = [n.key for n in neighbors if n.kind != "sub" and frequent[n.key]]
    return Neighborhood(x_support, subs, supers, [n.key for n in neighbors if not frequent[n.key]], counters)


@dataclass(frozen=True)
class Ask:
    """What to count for one pattern (key) on each graph.

    back, forward: super-patterns by edit, looked for in all mappings of key. subs: sub-patterns, tested on graphs that
    don't hold key. others: patterns tested on every graph. screen: test only graphs that hold all kinds of edges of
    what is tested. enough: once so many graphs of a task hold a super-pattern, it is no longer looked for there.
    """

    key: str
    back: tuple[tuple[tuple[int, int], str], ...] = ()
    forward: tuple[tuple[tuple[int, int], str], ...] = ()
    subs: tuple[str, ...] = ()
    others: tuple[str, ...] = ()
    own: bool = True
    screen: bool = True
    enough: int | None = None

    @staticmethod
    def larger(key: str, near: tuple[Neighbor, ...], **how) -> Ask:
        """C3c, C3d: all super-patterns of near, by the mappings of key."""
        edits = lambda kind: tuple((e, x.key) for x in near if x.kind == kind for e in x.edits)
        return Ask(key, edits("super_back"), edits("super_forward"), **how)


class Counter:
    """Counts of one Ask over the graphs of a task."""

    def __init__(self, ask: Ask):
        self.ask, self.x = ask, parse_key(ask.key)
        self.need = kinds_of(self.x) if ask.screen else set()
        self.back, self.forward = list(ask.back), dict(ask.forward)
        told = lambda keys: [(k, y, kinds_of(y) if ask.screen else set()) for k, y in zip(keys, map(parse_key, keys))]
        self.subs, self.others = told(ask.subs), told(ask.others)
        self.n: dict[str, int] = {ask.key: 0, **dict.fromkeys((*ask.subs, *ask.others), 0)}
        self.tests = 0

    def look(self, labels: list[int], near: list[set[int]], kinds: set[tuple[int, int]]) -> None:
        held = False
        if self.ask.own and self.need <= kinds:
            self.tests += 1
            held = self.grow(labels, near) if self.back or self.forward else contains(labels, near, self.x)
        if held:
            self.n[self.ask.key] += 1
        for k, y, need in self.others if held else (*self.subs, *self.others):
            if need <= kinds:
                self.tests += 1
                self.n[k] += contains(labels, near, y)

    def grow(self, labels: list[int], near: list[set[int]]) -> bool:
        hit: set[str] = set()
        held, most = [], len({*self.forward.values(), *(k for _, k in self.back)})

        def visit(m: tuple[int, ...]) -> bool:
            held[:] = [1]
            for (u, v), k in self.back:
                if m[v] in near[m[u]]:
                    hit.add(k)
            for at, image in enumerate(m):
                for w in near[image]:
                    if w not in m and (k := self.forward.get((at, labels[w]))):
                        hit.add(k)
            return len(hit) == most

        each_mapping(labels, near, self.x, visit)
        for k in hit:
            self.n[k] = self.n.get(k, 0) + 1
            if self.ask.enough and self.n[k] >= self.ask.enough:
                self.back = [e for e in self.back if e[1] != k]
                self.forward = {e: x for e, x in self.forward.items() if x != k}
        return bool(held)


def counted(packed: DataFrame, asks: list[Ask]) -> DataFrame:
    """ask (its place), pattern_key, n: graphs that hold what is asked for, in one scan, and tests, worked (nanoseconds).

    tests and worked stand in the row of the ask's own key; worked is of the whole scan, in the row of the first ask.
    Subs count the graphs that hold them and not the key. With a row of ask -1, whose n counts the graphs.
    """

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        counters, graphs, worked = [Counter(a) for a in asks], 0, 0
        for rows in arrays(batches):
            began = time.perf_counter_ns()
            graphs += len(rows)
            for labels, src, dst in rows:
                near = adjacency(len(labels), src, dst)
                kinds = {(labels[u], labels[v]) if labels[u] <= labels[v] else (labels[v], labels[u]) for u, v in zip(src, dst)}
                for c in counters:
                    c.look(labels, near, kinds)
            worked += time.perf_counter_ns() - began
        rows = [(-1, "", graphs, 0, 0)]
        for i, c in enumerate(counters):
            rows += [(i, k, n, c.tests * (k == c.ask.key), worked * (k == c.ask.key and not i)) for k, n in c.n.items()]
        yield pd.DataFrame(rows, columns=["ask", "pattern_key", "n", "tests", "worked"])

    every = packed.select("vlabel", "src", "dst").mapInPandas(count, "ask int, pattern_key string, n long, tests long, worked long")
    return every.groupBy("ask", "pattern_key").agg(*(F.sum(c).alias(c) for c in ("n", "tests", "worked")))


def grown_supports(packed: DataFrame, key: str, near: tuple[Neighbor, ...]) -> DataFrame:
    """C3c, C3d. pattern_key, support of a pattern and of its super-patterns of near that occur, from its own mappings."""
    return counted(packed, [Ask.larger(key, near)]).where("ask = 0").select("pattern_key", F.col("n").alias("support"))


def missed_supports(packed: DataFrame, key: str, subs: list[str]) -> DataFrame:
    """C3b. pattern_key, n: for each sub-pattern the graphs that hold it and don't hold the pattern."""
    return counted(packed, [Ask(key, subs=tuple(subs))]).where((F.col("ask") == 0) & (F.col("pattern_key") != key)).select("pattern_key", "n")


class DataExplorer:
    """Classes of neighbours counted on the data, for the walk and by themselves: C1, C2, C3, with C6.

    naive tests every neighbour on every graph. monotone tests the pattern and only the side that its own frequency
    doesn't decide. reuse looks for larger ones in the pattern's mappings and tests smaller ones only on graphs that may
    change their class. Whether a pattern is frequent is known already when it was met as a neighbour, so an exploration
    takes one job; otherwise, but for naive, its own support takes a job first. Several patterns share a job. With
    `known`, monotone and reuse don't count again what they have counted (at most `memory` patterns are remembered).
    jobs, tests, graphs (of a scan), worked (seconds in the tasks) and seconds add up over all explorations.
    """

    def __init__(self, packed: DataFrame, f: int, how: str = "reuse", ahead: int = 0, memory: int = 100_000):
        if how not in ("naive", "monotone", "reuse"):
            raise ValueError(f"no explorer {how}")
        self.packed, self.f, self.how, self.ahead = packed, f, how, ahead
        self.flags: Recent = Recent(memory)
        self.jobs = self.tests = self.graphs = 0
        self.worked = self.seconds = 0.0

    def _run(self, asks: list[Ask]) -> list[dict[str, int]]:
        began = time.perf_counter()
        out = [dict.fromkeys((a.key, *a.subs, *a.others), 0) for a in asks]  # no row comes from a database without partitions
        for r in counted(self.packed, asks).collect():  # a row for each pattern asked for
            if r["ask"] < 0:
                self.graphs = r.n
                continue
            out[r["ask"]][r.pattern_key] = r.n
            self.tests += r.tests
            self.worked += r.worked / 1e9
        self.jobs += 1
        self.seconds += time.perf_counter() - began
        return out

    def classify(self, wanted: dict[str, tuple[Neighbor, ...]]) -> dict[str, tuple[int, dict[str, bool]]]:
        """For each pattern, with the neighbours to decide: its support and whether each neighbour is frequent.

        Neighbours may be any patterns; one that isn't a sub- or super-pattern is tested.
        """
        if self.how == "naive":
            asks = [Ask(k, others=tuple(n.key for n in near), screen=False) for k, near in wanted.items()]
            found = dict(zip(wanted, self._run(asks), strict=True))
            out = {k: (n[k], {x.key: n[x.key] >= self.f for x in wanted[k]}) for k, n in found.items()}
        else:
            unsure, first = [k for k in wanted if k not in self.flags], {}
            if unsure:
                for k, n in zip(unsure, self._run([Ask(k, screen=self.how == "reuse") for k in unsure]), strict=True):
                    first[k] = n[k]
                    self.flags[k] = n[k] >= self.f
            side = {k: self._ask(k, near, self.flags[k], k not in first) for k, near in wanted.items()}
            found = dict(zip(wanted, self._run([ask for ask, _ in side.values()]), strict=True))
            out = {}
            for k, n in found.items():
                ask, decided = side[k]
                n[k] = n[k] if ask.own else first[k]
                held = lambda x: n.get(x, 0) + (n[k] if x in ask.subs else 0)  # noqa: B023, E731
                out[k] = n[k], {x.key: decided[x.key] if x.key in decided else held(x.key) >= self.f for x in wanted[k]}
        for k, (support, flags) in out.items():
            self.flags[k] = support >= self.f
            for x, flag in flags.items():
                self.flags[x] = flag
        return out

    def _ask(self, key: str, near: tuple[Neighbor, ...], frequent: bool, own: bool) -> tuple[Ask, dict[str, bool]]:
        """What is to be counted, and what is decided without."""
        decided, open_ = {}, []
        for x in near:
            smaller = x.kind == "sub" or (x.kind == "other" and within(x.key, key))
            larger = x.kind.startswith("super") or (x.kind == "other" and within(key, x.key))
            if (smaller and frequent) or (larger and not frequent):
                decided[x.key] = frequent
            else:
                open_.append((x, smaller))
        if self.how == "monotone":
            return Ask(key, others=tuple(x.key for x, _ in open_), own=own, screen=False), decided
        others = tuple(x.key for x, smaller in open_ if x.kind == "other" and not smaller)
        if frequent:
            return replace(Ask.larger(key, near, enough=self.f), others=others), decided
        return Ask(key, subs=tuple(x.key for x, smaller in open_ if smaller), others=others), decided


def _explore(packed: DataFrame, key: str, f: int, rules: PatternRules, how: str) -> Neighborhood:
    near, e = lattice_neighbors(key, rules), DataExplorer(packed, f, how)
    support, frequent = e.classify({key: near})[key]
    return _split(support, near, frequent, {"subgraph_tests": e.tests, "jobs": e.jobs, "worked": e.worked, "seconds": e.seconds})


def explore_naive(packed: DataFrame, key: str, f: int, rules: PatternRules) -> Neighborhood:
    """C1. Tests every neighbour on every graph."""
    return _explore(packed, key, f, rules, "naive")


def explore_monotone(packed: DataFrame, key: str, f: int, rules: PatternRules) -> Neighborhood:
    """C2. Sub-patterns of a frequent pattern are frequent, super-patterns of an infrequent one aren't; the rest is tested."""
    return _explore(packed, key, f, rules, "monotone")


def explore_reuse(packed: DataFrame, key: str, f: int, rules: PatternRules) -> Neighborhood:
    """C3. Decides all neighbours from the mappings of the pattern itself; what is tested is screened by kinds of edges."""
    return _explore(packed, key, f, rules, "reuse")


def label_histogram(packed: DataFrame) -> DataFrame:
    """gid, histogram: how many vertices of each label a graph has, as a map."""
    entries = "transform(array_distinct(vlabel), l -> struct(l as k, size(filter(vlabel, x -> x = l)) as n))"
    return packed.select("gid", F.expr(f"map_from_entries(filter({entries}, e -> e.k >= 0))").alias("histogram"))


def explore_table(supports: dict[str, int], key: str, f: int, rules: PatternRules) -> Neighborhood:
    """C5. Looks neighbours up in a table of supports: no tests, no jobs."""
    near = lattice_neighbors(key, rules)
    return _split(supports.get(key, 0), near, {x.key: supports.get(x.key, 0) >= f for x in near}, {"subgraph_tests": 0})


def forward_supports(found: DataFrame, h: DataFrame, width: int) -> DataFrame:
    """C3d. at, label, gid: where a mapping can grow by a vertex of a label outside its image."""
    m = found.select("gid", *(f"m{i}" for i in range(width)), F.posexplode(F.array(*(f"m{i}" for i in range(width)))).alias("at", "v"))
    return m.join(h.select("gid", "v", "w", "w_label"), ["gid", "v"]).where(" and ".join(f"w <> m{i}" for i in range(width))).select("at", F.col("w_label").alias("label"), "gid")


def back_supports(found: DataFrame, h: DataFrame, at: tuple[int, int]) -> DataFrame:
    """C3c. gid: where a mapping has an edge between the images of two vertices."""
    ends = h.select("gid", F.col("v").alias(f"m{at[0]}"), F.col("w").alias(f"m{at[1]}"))
    return found.join(ends, ["gid", f"m{at[0]}", f"m{at[1]}"], "left_semi").select("gid")


def sub_candidates(packed: DataFrame, h: DataFrame, key: str, sub: str) -> DataFrame:
    """C3b. gid: the graphs that hold all kinds of edges of a sub-pattern and don't hold the pattern."""
    return holding_kinds(packed, parse_key(sub)).join(match_pattern(h, parse_key(key)).select("gid").distinct(), "gid", "left_anti")


def explore_reuse_joins(g: GraphTables, packed: DataFrame, key: str, f: int, rules: PatternRules) -> Neighborhood:
    """C3, relational: the same by joins on graph and vertex, for graphs that don't fit a row.

    Frequent: sub-patterns need no test, and one join of the mappings with edges counts all super-patterns. Infrequent:
    super-patterns need no test, and sub-patterns are tested only on graphs with all their kinds of edges that don't
    hold the pattern.
    """
    near, p, h = lattice_neighbors(key, rules), parse_key(key), half_edges(packed).persist()
    found = match_pattern(h, p).persist()
    own = found.select("gid").distinct().count()
    tests, frequent = holding_kinds(packed, p).count(), {}
    if own >= f:
        frequent = {x.key: True for x in near if x.kind == "sub"}
        hits = []
        edit_key = {e: x.key for x in near for e in x.edits if x.kind == "super_forward"}
        if edit_key:
            table = packed.sparkSession.createDataFrame([(at, l, k) for (at, l), k in edit_key.items()], "at int, label int, pattern_key string")
            hits.append(forward_supports(found, h, len(p.labels)).join(F.broadcast(table), ["at", "label"]).select("pattern_key", "gid"))
        for x in near:
            for e in x.edits if x.kind == "super_back" else ():
                hits.append(back_supports(found, h, e).select(F.lit(x.key).alias("pattern_key"), "gid"))
        counts: dict[str, int] = {}
        if hits:
            every = hits[0]
            for more in hits[1:]:
                every = every.unionByName(more)
            counts = {r.pattern_key: r.n for r in every.distinct().groupBy("pattern_key").agg(F.count("*").alias("n")).collect()}
        frequent |= {x.key: counts.get(x.key, 0) >= f for x in near if x.kind != "sub"}
    else:
        frequent = {x.key: False for x in near if x.kind != "sub"}
        for x in (x for x in near if x.kind == "sub"):
            open_ = packed.join(sub_candidates(packed, h, key, x.key).select("gid"), "gid", "left_semi").persist()
            tests += open_.count()
            frequent[x.key] = own + support_many(open_, [x.key], also_graphs=True).count() >= f
            open_.unpersist()
    found.unpersist()
    h.unpersist()
    return _split(own, near, frequent, {"subgraph_tests": tests})


def neighbors_of(patterns: DataFrame, rules: PatternRules) -> DataFrame:
    """A5 as a lateral join: the columns of patterns (pattern_key among them), near_key, kind."""

    @udtf(returnType="near_key string, kind string")
    class Near:
        def eval(self, key: str):
            for n in lattice_neighbors(key, rules):
                yield n.key, n.kind

    return patterns.lateralJoin(Near(F.col("pattern_key").outer()))
