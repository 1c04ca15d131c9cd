"""Experiment workloads (X1-X10). A table of supports is made once; each row of a grid then runs one whole release.

Rows of the grid are independent repetitions and run in parallel; samples within a release never do. Experiments fix
their seeds; a release (`private_walk`) draws from the system's randomness.
"""

from __future__ import annotations

import random
import time
from collections.abc import Callable, Iterator
from itertools import product

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from latticewalk.functions.pattern import PatternRules, enumerate_space
from latticewalk.operators import graphs, walk
from latticewalk.sources import builders

MAIN = ("click", "dense", "profile")
#: Bounds of the patterns of each workload: nodes, edges.
BOUNDS = {"click": (4, 3), "dense": (3, 2), "profile": (3, 2), "role": (4, 3), "page": (3, 2), "ego": (3, 2)}
NAMES = {"click": builders.CLICK, "dense": builders.DENSE, "profile": builders.PROFILE, "role": builders.ROLES, "page": builders.TAGS, "ego": builders.EGO}
#: The table of supports is a dict on the driver up to so many patterns; beyond them a walk explores the data.
MOST_PATTERNS = 2_000_000
#: Spaces: patterns of one edge and more; single vertices too; the smallest patterns as neighbours of each other.
LATTICES = ("plain", "vertices", "bridged")


def rules_of(name: str, lattice: str = "plain") -> PatternRules:
    nodes, edges = BOUNDS[name]
    least = (1, 0) if lattice == "vertices" else (2, 1)
    return PatternRules(tuple(range(len(NAMES[name]))), nodes, edges, *least)


def packed_of(spark: SparkSession, sf_dir: str, name: str, percent: int = 100) -> DataFrame:
    """The packed graphs of a workload, or a stable, nested share of them."""
    packed = graphs.pack(builders.WORKLOADS[name](spark, sf_dir))
    return packed if percent == 100 else packed.where(F.pmod(F.xxhash64("gid"), F.lit(100)) < percent)


def table_of(supports: DataFrame) -> dict[str, int]:
    """The supports as a dict, behind a check of their number."""
    rows = supports.limit(MOST_PATTERNS + 1).collect()
    if len(rows) > MOST_PATTERNS:
        raise ValueError("too many patterns for a table on the driver; explore the data")
    return {r.pattern_key: r.support for r in rows}


def supports_of(spark: SparkSession, sf_dir: str, name: str, percent: int = 100, lattice: str = "plain") -> dict[str, int]:
    return table_of(graphs.mine_supports(packed_of(spark, sf_dir, name, percent), rules_of(name, lattice)))


def supports_by(spark: SparkSession, sf_dir: str, name: str, lattices, percent: int = 100) -> dict[str, dict[str, int]]:
    """The supports of each lattice: the space from single vertices holds the others, so the data are read once."""
    every = supports_of(spark, sf_dir, name, percent, "vertices" if "vertices" in lattices else "plain")
    edges = {k: n for k, n in every.items() if "-" in k}
    return {la: every if la == "vertices" else edges for la in lattices}


def threshold(supports: dict[str, int], k: int) -> int:
    """E4. The support of the k-th pattern."""
    return sorted(supports.values(), reverse=True)[:k][-1]


def service_of(packed: DataFrame, rules: PatternRules, k: int, explorer: str = "auto", f: int | None = None, ahead: int = 64):
    """A service for the walk, with its threshold (of the k-th pattern, if f isn't given).

    auto: a table of supports where it fits the driver, else the reuse explorer on the data; or table, naive, monotone,
    reuse. Any number of patterns can be walked.
    """
    if explorer in ("naive", "monotone", "reuse") and f is not None:
        return graphs.DataExplorer(packed, f, explorer, ahead)
    mined = graphs.mine_supports(packed, rules).persist()
    try:
        if f is None:
            f = graphs.top_k(mined, k).agg(F.min("support")).first()[0] or 1
        if explorer == "table" or (explorer == "auto" and mined.limit(MOST_PATTERNS + 1).count() <= MOST_PATTERNS):
            return walk.Materialized(table_of(mined), f)
        return graphs.DataExplorer(packed, f, "reuse" if explorer == "auto" else explorer, ahead)
    finally:
        mined.unpersist()


def in_parallel(spark: SparkSession, n: int, task: Callable[[int, object], list[tuple]], schema: str, shared: object) -> DataFrame:
    """The rows that task(i, shared) gives for each i below n. What is shared goes to every task."""
    sent = spark.sparkContext.broadcast(shared)
    names = [c.split()[0] for c in schema.split(", ")]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for i in batch["id"]:
                rows = task(int(i), sent.value)
                if rows:
                    yield pd.DataFrame(rows, columns=names)

    return spark.range(0, n, 1, max(1, min(n, spark.sparkContext.defaultParallelism * 4))).mapInPandas(run, schema)


def config_of(g: dict, f: int) -> walk.WalkConfig:
    lattice = g.get("lattice", "plain")
    return walk.WalkConfig(
        rules_of(g["workload"], lattice),
        k=g.get("k", 15),
        f=f,
        eps1=g.get("eps", 0.5),
        score=g.get("score", "linear"),
        eta=g.get("eta", 0.9),
        rho=g.get("rho", 0.5),
        bridge=lattice == "bridged",
        seed=g["rep"] * 1009 + 17,
        max_steps=20_000,
    )


RESULTS = "workload string, param string, value string, rep int, metric string, measure double"


def run_grid(spark: SparkSession, grid: list[dict], tables: dict) -> DataFrame:
    """workload, param, value, rep, metric, measure: one release for each row of the grid, in parallel.

    tables: (workload, lattice, percent) -> supports. They are sent to every task, so their total is checked.
    """
    if sum(map(len, tables.values())) > MOST_PATTERNS:
        raise ValueError("too many patterns to broadcast")

    def task(i: int, tables: dict) -> list[tuple]:
        g = grid[i]
        s = tables[g["workload"], g.get("lattice", "plain"), g.get("percent", 100)]
        config = config_of(g, threshold(s, g.get("k", 15)))
        began = time.perf_counter()
        try:
            r = walk.sample_private_patterns(walk.Materialized(s), config)
        except walk.NotConverged:  # nothing is released, and that is the result
            return [(g["workload"], g["param"], g["value"], g["rep"], "released", 0.0)]
        took = time.perf_counter() - began
        m = walk.metrics(r.patterns, s, config.k)
        m |= {"released": 1.0, "acceptance": sum(t[7] for t in r.trace) / len(r.trace), "steps": sum(r.steps) / len(r.steps)}
        m |= {"seconds_per_pattern": took / config.k, "seconds_per_iteration": took / len(r.trace)}
        return [(g["workload"], g["param"], g["value"], g["rep"], k, float(v)) for k, v in m.items()]

    return in_parallel(spark, len(grid), task, RESULTS, tables)


def summary(results: DataFrame) -> DataFrame:
    """Mean and standard error over repetitions."""
    of = [F.count("*").alias("reps"), F.avg("measure").alias("mean"), (F.stddev_samp("measure") / F.sqrt(F.count("*"))).alias("std_error")]
    return results.groupBy("workload", "param", "value", "metric").agg(*of)


def summary_rollup(results: DataFrame) -> DataFrame:
    """Means by metric, workload and value, by metric and workload, and by metric; null stands for all."""
    by = results.rollup("metric", "workload", "value").agg(F.count("*").alias("n"), F.round(F.avg("measure"), 9).alias("mean"))
    return by.where("metric is not null")


def sweep(spark: SparkSession, sf_dir: str, params: dict[str, list], workloads: tuple[str, ...] = MAIN, reps: int = 5) -> DataFrame:
    """Some parameters move, the others keep their defaults (X8: eps 0.5, k 15, no noisy supports, plain lattice)."""
    lattices, percents = params.get("lattice", ["plain"]), params.get("percent", [100])
    tables = {(w, la, p): s for w in workloads for p in percents for la, s in supports_by(spark, sf_dir, w, lattices, p).items()}
    name, grid = ",".join(params), []
    for w, values, rep in product(workloads, product(*params.values()), range(reps)):
        grid.append({"workload": w, "param": name, "value": ",".join(map(str, values)), "rep": rep, **dict(zip(params, values))})
    return summary(run_grid(spark, grid, tables))


def convergence_traces(spark: SparkSession, sf_dir: str, workload: str = "profile", chains: int = 20, lattice: str = "plain") -> DataFrame:
    """Chain, step, z of the three metrics, for the first sample of independent chains, which run in parallel."""
    s = supports_of(spark, sf_dir, workload, lattice=lattice)
    g = {"workload": workload, "lattice": lattice}

    def task(c: int, s: dict) -> list[tuple]:
        config = config_of({**g, "rep": c}, threshold(s, 15))
        trace = walk.Walker(walk.Materialized(s), config).chain(c + 1, random.Random(1000 + c))[2]
        return [(c + 1, t[1], *map(float, t[11:14]), bool(t[7])) for t in trace]

    return in_parallel(spark, chains, task, "chain int, step int, z_neighbors double, z_frequent double, z_nodes double, accepted boolean", s)


TRACE = "workload string, explorer string, step int, at string, proposed string, q_xy double, q_yx double, alpha double, accepted boolean, support long, n_neighbors int, n_frequent int, jobs int, subgraph_tests long, worker_seconds double, seconds double"


def walk_by_explorer(spark: SparkSession, sf_dir: str, workloads: tuple[str, ...] = MAIN, steps: int = 8, k: int = 15, seed: int = 11, explorers: tuple[str, ...] = ("table", "reuse", "monotone", "naive")) -> DataFrame:
    """The same seeded walk behind each explorer on the packed graphs, a row for each step and what it cost.

    Explored patterns are remembered, by all explorers alike. seconds is the time of the step, worker_seconds what the
    tasks spent on graphs in it, without the fixed cost of a job.
    """
    rows = []
    for workload in workloads:
        rules, packed = rules_of(workload), packed_of(spark, sf_dir, workload).persist()
        table = service_of(packed, rules, k, "table")
        config = walk.WalkConfig(rules, k=k, f=table.f, seed=seed)
        for name in explorers:
            service = table if name == "table" else graphs.DataExplorer(packed, table.f, name)
            walker, r = walk.Walker(service, config), config.randomness()
            x = walker.start(r)
            for step in range(1, steps + 1):
                before, began, at = (service.jobs, service.tests, service.worked), time.perf_counter(), x
                walker.explore(x)
                x, y, q, back, a, ok = walker.step(x, r)
                support, sub, sup, rest = walker.explore(x)
                cost = (service.jobs - before[0], service.tests - before[1], service.worked - before[2], time.perf_counter() - began)
                rows.append((workload, name, step, at, y, q, back, a, ok, support, len(sub) + len(sup) + len(rest), len(sub) + len(sup), *cost))
        packed.unpersist()
    return spark.createDataFrame(rows, TRACE)


def walk_costs(spark: SparkSession, sf_dir: str, **how) -> DataFrame:
    """Means of walk_by_explorer over the steps that explored a pattern, and how many times those of naive."""
    t = walk_by_explorer(spark, sf_dir, **how)
    own = t.groupBy("workload", "explorer").agg(*(F.sum(c).alias(c) for c in ("jobs", "subgraph_tests", "worker_seconds", "seconds")))
    naive = own.where("explorer = 'naive'").select("workload", *(F.col(c).alias(f"naive_{c}") for c in ("subgraph_tests", "worker_seconds", "seconds")))
    ratio = lambda c: F.round(F.col(f"naive_{c}") / F.nullif(F.col(c), F.lit(0)), 2).alias(f"{c}_saved")
    return own.join(F.broadcast(naive), "workload").select("workload", "explorer", "jobs", "subgraph_tests", "worker_seconds", "seconds", ratio("subgraph_tests"), ratio("worker_seconds"), ratio("seconds"))


def explorer_comparison(spark: SparkSession, sf_dir: str, workloads: tuple[str, ...] = MAIN) -> DataFrame:
    """Seconds and subgraph tests of each explorer on the same states; all must return the same neighbourhood.

    States: the most supported pattern, one well below the threshold, and one of the most edges just below it.
    """
    rows = []
    for workload in workloads:
        rules = rules_of(workload)
        packed = packed_of(spark, sf_dir, workload).persist()
        s = table_of(graphs.mine_supports(packed, rules))
        f = threshold(s, 15)
        ranked = sorted(s, key=lambda k: (-s[k], k))
        large = [k for k in ranked if s[k] < f and k.count("-") == rules.max_edges]
        for key in dict.fromkeys([ranked[0], ranked[min(len(ranked) - 1, 40)], *large[:1]]):
            ways = {"naive": graphs.explore_naive, "monotone": graphs.explore_monotone, "reuse": graphs.explore_reuse}
            for name in (*ways, "table"):
                began = time.perf_counter()
                n = ways[name](packed, key, f, rules) if name in ways else graphs.explore_table(s, key, f, rules)
                rows.append((workload, key, name, n.support, len(n.freq_sub), len(n.freq_super), len(n.infreq), n.counters["subgraph_tests"], float(n.counters.get("worked", 0)), time.perf_counter() - began))
        packed.unpersist()
    return spark.createDataFrame(rows, "workload string, pattern_key string, explorer string, support long, freq_sub int, freq_super int, infreq int, subgraph_tests long, worker_seconds double, seconds double")


def time_by_size(spark: SparkSession, sf_dir: str, workloads: tuple[str, ...] = MAIN, percents: tuple[int, ...] = (25, 50, 100), k: int = 1, ahead: int = 64) -> DataFrame:
    """Time of whole chains until their pattern is out, on shares of the data, by the reuse explorer on the graphs.

    The explorer looks ahead: a job explores up to `ahead` neighbours of the state besides the one asked for. No table of supports is used but for
    the threshold, as the reference takes it from a miner.
    """
    rows = []
    for workload, percent in product(workloads, percents):
        packed = packed_of(spark, sf_dir, workload, percent).persist()
        f = service_of(packed, rules_of(workload), 15, "table").f
        service = graphs.DataExplorer(packed, f, "reuse", ahead)
        r = walk.sample_private_patterns(service, walk.WalkConfig(rules_of(workload), k=k, f=f, eps1=0.5 * k / 15, seed=23))
        rows.append((workload, percent, service.graphs, sum(r.seconds) / k, sum(r.seconds) / len(r.trace), service.worked / k, service.jobs, service.tests, len(r.trace)))
        packed.unpersist()
    return spark.createDataFrame(rows, "workload string, percent int, graphs long, seconds_per_pattern double, seconds_per_iteration double, worker_seconds_per_pattern double, jobs int, subgraph_tests long, steps int")


def scaling_fit(times: DataFrame) -> DataFrame:
    """A line of time against the number of graphs for each workload (columns workload, graphs and times)."""
    measures = [c for c in times.columns if "seconds" in c]
    long = times.select("workload", "graphs", F.expr(f"stack({len(measures)}, " + ", ".join(f"'{c}', {c}" for c in measures) + ") as (measure, t)"))
    x, y = F.col("graphs").cast("double"), F.col("t")
    return long.groupBy("workload", "measure").agg(F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2"))


def first_samples(spark: SparkSession, sf_dir: str, workload: str, draws: int, lattice: str) -> tuple[DataFrame, dict[str, float]]:
    """The first sample of independent chains (pattern_key), and the exact law, in a space of at most two edges.

    A chain that doesn't converge gives null.
    """
    s = supports_of(spark, sf_dir, workload, lattice=lattice)
    small = rules_of(workload, lattice)
    small = PatternRules(small.labels, 3, 2, small.min_nodes, small.min_edges)
    space = enumerate_space(small)
    own = {k: s.get(k, 0) for k in space}
    config = walk.WalkConfig(small, k=1, f=threshold(own, 15), eps1=0.02, min_steps=150, bridge=lattice == "bridged")

    def task(d: int, s: dict) -> list[tuple]:
        try:
            return [(walk.Walker(walk.Materialized(s), config).chain(1, random.Random(d))[0],)]
        except walk.NotConverged:
            return [(None,)]

    return in_parallel(spark, draws, task, "pattern_key string", own), walk.exponential_probs(space, own, config.eps1, config.k)


def exact_vs_walk(spark: SparkSession, sf_dir: str, workload: str = "click", draws: int = 300, lattice: str = "plain") -> DataFrame:
    """How often each pattern is the first sample of a walk, beside the exact mechanism's law."""
    samples, law = first_samples(spark, sf_dir, workload, draws, lattice)
    hits = {r.pattern_key: r["count"] for r in samples.where("pattern_key is not null").groupBy("pattern_key").count().collect()}
    return spark.createDataFrame([(workload, k, float(p), hits.get(k, 0) / draws) for k, p in law.items()], "workload string, pattern_key string, exact double, walked double")


def exact_vs_walk_distance(spark: SparkSession, sf_dir: str, workloads: tuple[str, ...] = MAIN, draws: int = 200, lattices: tuple[str, ...] = LATTICES) -> DataFrame:
    """Distance of the walk's first samples from the exact law, in total variation and as a chi-square per pattern.

    expected_tv is what as many draws from the exact law itself would show, over 20 repetitions. draws are the chains that
    converged; without any the distances are null.
    """
    rows = []
    for workload, lattice in product(workloads, lattices):
        samples, law = first_samples(spark, sf_dir, workload, draws, lattice)
        hits = {r.pattern_key: r["count"] for r in samples.where("pattern_key is not null").groupBy("pattern_key").count().collect()}
        n = sum(hits.values())
        if not n:
            rows.append((workload, lattice, 0, None, None, None))
            continue
        walked = {k: c / n for k, c in hits.items()}
        chi = sum((hits.get(k, 0) - n * p) ** 2 / (n * p) for k, p in law.items() if p > 0) / max(1, len(law) - 1)
        r, keys, weights, base = random.Random(3), list(law), list(law.values()), []
        for _ in range(20):
            drawn = r.choices(keys, weights, k=n)
            base.append(walk.tv_between({k: drawn.count(k) / n for k in set(drawn)}, law))
        rows.append((workload, lattice, n, walk.tv_between(walked, law), sum(base) / len(base), float(chi)))
    return spark.createDataFrame(rows, "workload string, lattice string, draws int, tv double, expected_tv double, chi2_per_pattern double")


def tv_after_steps(spark: SparkSession, sf_dir: str, workloads: tuple[str, ...] = MAIN, steps: tuple[int, ...] = (1, 20, 40, 75, 150, 500, 2000), lattices: tuple[str, ...] = LATTICES) -> DataFrame:
    """Distance of the first chain's law from its limit after some steps, and the delta that it leaves.

    From the exact transition matrix of each lattice, workloads in parallel; for spaces whose matrix fits a task.
    """
    cases = [*product(workloads, lattices)]
    tables = {(w, la): s for w in workloads for la, s in supports_by(spark, sf_dir, w, lattices).items()}

    def task(i: int, tables: dict) -> list[tuple]:
        import numpy as np

        workload, lattice = cases[i]
        s, rules = tables[workload, lattice], rules_of(workload, lattice)
        space = enumerate_space(rules)
        if len(space) > 4_000:
            raise ValueError("too many patterns for a transition matrix")
        walker = walk.Walker(walk.Materialized(s), config_of({"workload": workload, "lattice": lattice, "rep": 0}, threshold(s, 15)))
        law = np.array([*walk.exponential_probs(space, s, walker.config.eps1, walker.config.k).values()])
        least = min(k.count("-") for k in space)
        now, rows = np.array([float(k.count("-") == least) for k in space]), []
        now, matrix = now / now.sum(), walk.transition_matrix(walker, space)
        for step in range(1, max(steps) + 1):
            now = now @ matrix
            if step in steps:
                tv = walk.tv_distance(now, law)
                rows.append((workload, lattice, step, float(tv), min(1.0, walk.delta_for(tv, walker.config.eps1, walker.config.k))))
        return rows

    return in_parallel(spark, len(cases), task, "workload string, lattice string, step int, tv double, delta double", tables)


def measured_ledger(spark: SparkSession, sf_dir: str, workload: str = "click", k: int = 15, chains: int = 3, lattices: tuple[str, ...] = LATTICES) -> DataFrame:
    """For the first chains of a seeded release, the distance from their laws when they stopped, and the delta of it.

    What a ledger may claim if the space is small enough to be enumerated; each chain's law is that of the space left.
    """
    cases = [*lattices]
    tables = supports_by(spark, sf_dir, workload, cases)

    def task(i: int, tables: dict) -> list[tuple]:
        lattice, s = cases[i], tables[cases[i]]
        config = config_of({"workload": workload, "lattice": lattice, "rep": 1, "k": k}, threshold(s, k))
        walker, r, space, rows = walk.Walker(walk.Materialized(s), config), config.randomness(), enumerate_space(config.rules), []
        for number in range(1, chains + 1):
            key, steps, _ = walker.chain(number, r)
            theta = walk.chain_distance(walker, space, steps)
            rows.append((workload, lattice, number, steps, theta, config.eps1 / k, min(1.0, walk.delta_for(theta, config.eps1, k))))
            walker.lattice.remove(key)
            walker.classes_of.clear()
        return rows

    return in_parallel(spark, len(cases), task, "workload string, lattice string, chain int, steps int, theta double, eps double, delta double", tables)


def private_walk(spark: SparkSession, sf_dir: str, workload: str, k: int = 15, eps2: float | None = None, explorer: str = "auto", lattice: str = "plain", seed: int | None = None) -> DataFrame:
    """E3. The release of a workload: secret randomness unless a seed is given. No rows if a chain doesn't converge."""
    rules, packed = rules_of(workload, lattice), packed_of(spark, sf_dir, workload).persist()
    try:
        service = service_of(packed, rules, k, explorer)
        config = walk.WalkConfig(rules, k=k, f=service.f, eps2=eps2, f_source="exact", bridge=lattice == "bridged", seed=seed, max_steps=20_000)
        return walk.sample_private_patterns(service, config).to_df(spark)
    except walk.NotConverged:
        return walk.Release([], [], walk.BudgetLedger()).to_df(spark)
    finally:
        packed.unpersist()
