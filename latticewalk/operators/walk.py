"""The private pattern walk: scores, proposals, acceptance, removal, convergence (D1-D14) and whole releases.

The chain itself is driver control flow over a service that classifies neighbourhoods: from a table of supports made in
one scan (`Materialized`), from supports asked for when needed (`OnDemand`, `Frontier`), or by one of the explorers on
the data (`graphs.DataExplorer`: naive, monotone, reuse). Neighbours are ordered by key before drawing, so every service
gives the same chain for a seed.
"""

from __future__ import annotations

import math
import random
import time
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field, replace
from fractions import Fraction

from latticewalk.functions.pattern import Neighbor, PatternRules, Recent, enumerate_space, lattice_neighbors, parse_key


# ---- D1-D3 ----
def linear(f: int) -> tuple[Callable[[float], float], float]:
    return (lambda s: float(s)), 1.0


def plateau(f: int) -> tuple[Callable[[float], float], float]:
    return (lambda s: float(min(s, f))), 1.0


def steep(f: int, a: float = 0.5, b: float = 1.0) -> tuple[Callable[[float], float], float]:
    """The sensitivity is that of the jump from f - 1 to f, or 1."""
    return (lambda s: float(s) if s >= f else a * (s - b)), max(1.0, (1 - a) * f + a * (1 + b))


SCORES = {"linear": linear, "plateau": plateau, "steep": steep}


# ---- D4-D6 ----
def balanced_masses(n_sub: int, n_super: int, n_infreq: int, eta: float, rho: float) -> tuple[float, float, float]:
    """D5, D6. Mass of each class of neighbours; what an empty class would get goes to the others."""
    if not n_sub and not n_super:
        return (0.0, 0.0, 1.0 if n_infreq else 0.0)
    rho = 0.0 if not n_sub else 1.0 if not n_super else rho
    eta = 1.0 if not n_infreq else eta
    return (eta * rho, eta * (1 - rho), 1 - eta)


def alpha(u_x: float, u_y: float, q_xy: float, q_yx: float, eps1: float, k: int, delta_u: float = 1.0) -> float:
    """D7. Acceptance probability, in logs."""
    if q_yx <= 0:
        return 0.0
    log_ratio = eps1 * (u_y - u_x) / (2 * k * delta_u) + math.log(q_yx) - math.log(q_xy)
    return math.exp(min(0.0, log_ratio))


# ---- support services ----
class BySupport:
    """Classes of neighbours from the supports of patterns, which a subclass knows."""

    ahead = 0

    def __init__(self, f: int | None = None):
        self.f, self.jobs, self.tests = f, 0, 0
        self.worked = self.seconds = 0.0

    def of(self, keys: Iterable[str]) -> dict[str, int]:
        raise NotImplementedError

    def classify(self, wanted: dict[str, tuple[Neighbor, ...]]) -> dict[str, tuple[int, dict[str, bool]]]:
        out = {}
        for key, near in wanted.items():
            s = self.of([key, *(n.key for n in near)])
            out[key] = s[key], {n.key: s[n.key] >= self.f for n in near}
        return out


class Materialized(BySupport):
    """Supports of all patterns that occur, from one scan; others have support 0."""

    def __init__(self, supports: dict[str, int], f: int | None = None):
        super().__init__(f)
        self.supports = supports

    def of(self, keys: Iterable[str]) -> dict[str, int]:
        return {k: self.supports.get(k, 0) for k in keys}


class OnDemand(BySupport):
    """Supports asked from the data when the walk needs them; those used least recently are forgotten."""

    def __init__(self, count: Callable[[list[str]], dict[str, int]], memory: int = 100_000, f: int | None = None):
        super().__init__(f)
        self.count, self.known = count, Recent(memory)

    def of(self, keys: Iterable[str]) -> dict[str, int]:
        keys = list(keys)
        found = {k: self.known[k] for k in keys if k in self.known}
        new = [k for k in keys if k not in found]
        if new:
            self.jobs += 1
            counts = self.count(new)
            for k in new:
                found[k] = self.known[k] = counts.get(k, 0)
        return found


class Frontier(OnDemand):
    """Asks for the neighbourhoods of the wanted patterns in the same job, so that a walk needs fewer jobs.

    `most` bounds the patterns of one job that weren't asked for; a pattern left out is asked for when it is needed.
    """

    def __init__(self, count: Callable[[list[str]], dict[str, int]], rules: PatternRules, most: int = 5_000, memory: int = 100_000, f: int | None = None):
        super().__init__(count, memory, f)
        self.rules, self.most = rules, most

    def of(self, keys: Iterable[str]) -> dict[str, int]:
        keys = list(keys)
        if any(k not in self.known for k in keys):
            more = dict.fromkeys(n.key for k in keys for n in lattice_neighbors(k, self.rules))
            super().of([*keys, *[k for k in more if k not in self.known][: self.most]])
        return super().of(keys)


# ---- D12-D14 ----
def geweke_z(series: list[float], first: float = 0.1, last: float = 0.5, var: str = "sample") -> float:
    """D12. Difference of the means of the first and last parts over the root of summed variances.

    var: of the values ("sample", as in the reference), or of the means ("mean"), or of the means with
    autocorrelation ("spectral"), which are stricter. Without variance: 0 if the means agree, else infinite.
    """
    n = len(series)
    a, b = series[: max(1, int(n * first))], series[n - max(1, int(n * last)) :]
    mean = lambda x: sum(x) / len(x)

    def spread(x: list[float]) -> float:
        m = mean(x)
        v = sum((y - m) ** 2 for y in x) / (len(x) - 1) if len(x) > 1 else 0.0
        if var == "sample":
            return v
        if var == "spectral":
            lags = min(len(x) - 1, int(2 * len(x) ** (1 / 3)))
            cov = lambda l: sum((x[i] - m) * (x[i + l] - m) for i in range(len(x) - l)) / len(x)
            v = max(0.0, cov(0) + 2 * sum((1 - l / (lags + 1)) * cov(l) for l in range(1, lags + 1)))
        return v / len(x)

    d, v = mean(a) - mean(b), spread(a) + spread(b)
    return (0.0 if d == 0 else math.copysign(math.inf, d)) if v <= 0 else d / math.sqrt(v)


def gelman_rubin(chains: list[list[float]]) -> float:
    """D14. Potential scale reduction of several chains; those of a single value have no variance and are left out.

    Variances within count by their degrees of freedom, means by their lengths, and the length is the mean length: the
    usual figure where all lengths are equal.
    """
    chains = [c for c in chains if len(c) > 1]
    sizes, means = [len(c) for c in chains], [sum(c) / len(c) for c in chains]
    n, grand = sum(sizes) / len(chains), sum(map(sum, chains)) / sum(sizes)
    w = sum(sum((y - x) ** 2 for y in c) for c, x in zip(chains, means)) / (sum(sizes) - len(chains))
    b = sum(k * (x - grand) ** 2 for k, x in zip(sizes, means)) / (len(chains) - 1)
    return math.sqrt(((n - 1) / n * w + b / n) / w) if w else 1.0


class Convergence:
    """D13. All metrics within [-1, 1] for `run` steps in a row; sums are kept so that a step costs little."""

    def __init__(self, metrics: int = 3, run: int = 20, bound: float = 1.0):
        self.sums = [[0.0] for _ in range(metrics)]
        self.squares = [[0.0] for _ in range(metrics)]
        self.run, self.bound, self.good, self.z = run, bound, 0, [0.0] * metrics

    def add(self, values: tuple[float, ...]) -> bool:
        for j, v in enumerate(values):
            self.sums[j].append(self.sums[j][-1] + v)
            self.squares[j].append(self.squares[j][-1] + v * v)
        n = len(self.sums[0]) - 1
        a, b = max(1, n // 10), max(1, n // 2)
        ok = n >= 10
        for j in range(len(values)):
            s, q = self.sums[j], self.squares[j]
            ma, mb = s[a] / a, (s[n] - s[n - b]) / b
            va = max(0.0, (q[a] - a * ma * ma) / (a - 1)) if a > 1 else 0.0
            vb = max(0.0, (q[n] - q[n - b] - b * mb * mb) / (b - 1)) if b > 1 else 0.0
            d, v = ma - mb, va + vb
            self.z[j] = (0.0 if abs(d) < 1e-12 else math.copysign(math.inf, d)) if v <= 1e-12 else d / math.sqrt(v)
            ok = ok and abs(self.z[j]) <= self.bound
        self.good = self.good + 1 if ok else 0
        return self.good >= self.run


@dataclass(frozen=True)
class WalkConfig:
    """seed: None draws from the system's randomness, as a release must; tests and experiments fix it.

    start: a pattern, or None for a random one of the least size. bridge: see PunchedLattice. contribution: the most
    graphs that one person may have; scores and supports then move by so many at once. theta: a bound that the caller
    vouches for on each chain's distance from its law; without one, the ledger claims no (eps, delta).
    """

    rules: PatternRules
    k: int = 15
    f: int = 1
    eps1: float = 0.5
    eps2: float | None = None
    score: str = "linear"
    eta: float = 0.9
    rho: float = 0.5
    proposal: str = "balanced"
    seed: int | None = None
    min_steps: int = 40
    max_steps: int = 3000
    lazy: float = 0.0
    start: str | None = None
    f_source: str = "given"
    bridge: bool = False
    noise: str = "discrete"
    contribution: int = 1
    theta: float | None = None
    memory: int = 100_000

    def randomness(self) -> random.Random:
        return random.SystemRandom() if self.seed is None else random.Random(self.seed)


class BudgetLedger:
    """E9, E10. Spent budget by phase; sums of eps, and of delta for approximate steps.

    ideal is what holds if every chain ends at its law; total adds what is known of their distance from it: a delta of 1
    stands for no bound.
    """

    def __init__(self):
        self.rows: list[tuple[str, float, float]] = []
        self.off_law = 0.0

    def spend(self, phase: str, eps: float, delta: float = 0.0) -> None:
        if eps < 0 or delta < 0:
            raise ValueError("a budget can't be negative")
        self.rows.append((phase, eps, delta))

    def away(self, k: int, eps1: float, theta: float | None) -> None:
        """E6. What k chains at a distance of at most theta from their laws add; None: not known."""
        self.off_law = 1.0 if theta is None else min(1.0, k * delta_for(theta, eps1, k))
        self.rows.append(("distance of the chains from their laws" + (": not bounded" if theta is None else ""), 0.0, self.off_law))

    @property
    def total(self) -> tuple[float, float]:
        return sum(r[1] for r in self.rows), min(1.0, sum(r[2] for r in self.rows))

    @property
    def ideal(self) -> tuple[float, float]:
        return self.total[0], sum(r[2] for r in self.rows) - self.off_law

    def to_df(self, spark):
        return spark.createDataFrame(self.rows, "phase string, eps double, delta double")


@dataclass
class Release:
    """What leaves: rank, pattern, noisy support if paid for. The trace, its costs and true supports stay inside."""

    patterns: list[str]
    noisy: list[float | None]
    ledger: BudgetLedger
    trace: list[tuple] = field(default_factory=list, repr=False)
    steps: list[int] = field(default_factory=list, repr=False)
    seconds: list[float] = field(default_factory=list, repr=False)

    def to_df(self, spark):
        rows = []
        for i, (key, noisy) in enumerate(zip(self.patterns, self.noisy)):
            p = parse_key(key)
            rows.append((i + 1, key, list(p.labels), [(u, v, 0) for u, v in p.edges], noisy))
        return spark.createDataFrame(rows, "rank int, pattern_key string, vlabel array<int>, edges array<struct<u:int,v:int,elabel:int>>, noisy_support double")


class PunchedLattice:
    """D10. Neighbours in the space without released patterns: a removed neighbour is replaced by its own, transitively.

    With `bridge`, patterns one edge (or vertex) below the smallest size count as removed from the start, so the smallest
    patterns of the space neighbour each other through what they share. The relation stays symmetric, hence the chain's
    law is the same; without it, a walk leaves a smallest pattern only through less supported ones.
    """

    def __init__(self, rules: PatternRules, bridge: bool = False):
        self.rules, self.removed = rules, set()
        self.wide = replace(rules, min_nodes=max(1, rules.min_nodes - 1), min_edges=max(0, rules.min_edges - 1)) if bridge else rules
        self.memo: dict[str, tuple[str, ...]] = {}

    def remove(self, key: str) -> None:
        self.removed.add(key)
        self.memo.clear()

    def around(self, key: str) -> tuple[Neighbor, ...]:
        """The neighbours in order of key, with their kinds and edits; a substitute's kind is "other"."""
        found = self.memo.get(key)
        if found is None:
            direct, seen, out, todo = {n.key: n for n in lattice_neighbors(key, self.rules)}, {key}, set(), [key]
            while todo:
                for n in lattice_neighbors(todo.pop(), self.wide):
                    if n.key in seen:
                        continue
                    seen.add(n.key)
                    if n.key in self.removed or (self.wide is not self.rules and not self.rules.allows(parse_key(n.key))):
                        todo.append(n.key)
                    else:
                        out.add(n.key)
            found = self.memo[key] = tuple(direct.get(k) or Neighbor(k, "other", ()) for k in sorted(out))
        return found

    def neighbors(self, key: str) -> tuple[str, ...]:
        return tuple(n.key for n in self.around(key))


def joined(lattice: PunchedLattice, space: list[str]) -> bool:
    """A10. Whether a walk can get from each pattern of the space that is left to every other."""
    left = {k for k in space if k not in lattice.removed}
    todo = [min(left)] if left else []
    left -= {*todo}
    while todo:
        near = left.intersection(lattice.neighbors(todo.pop()))
        left -= near
        todo += near
    return not left


class NotConverged(RuntimeError):
    """A chain used up its steps; no pattern may leave."""


class Walker:
    """A chain over the patterns of a space, by what the service says of their neighbourhoods."""

    def __init__(self, service, config: WalkConfig):
        self.service, self.config, self.lattice = service, config, PunchedLattice(config.rules, config.bridge)
        if service.f is None:
            service.f = config.f
        if service.f != config.f:
            raise ValueError("the service classifies by another threshold")
        self.utility, delta_u = SCORES[config.score](config.f)
        self.delta_u = delta_u * config.contribution
        self.classes_of: Recent = Recent(config.memory)

    def explore(self, key: str, soon: Iterable[str] = ()) -> tuple[int, list[str], list[str], list[str]]:
        """Support, and frequent smaller, frequent larger and infrequent neighbours, each in order of key.

        soon: patterns that may be asked for next; if the service looks ahead, they share the job.
        """
        if key not in self.classes_of:
            more = [k for k in soon if k != key and k not in self.classes_of][: self.service.ahead]
            wanted = {k: self.lattice.around(k) for k in (key, *more)}
            for k, (support, frequent) in self.service.classify(wanted).items():
                near, size = [n.key for n in wanted[k]], k.count("-")
                sub = [n for n in near if frequent[n] and n.count("-") < size]
                sup = [n for n in near if frequent[n] and n.count("-") >= size]
                self.classes_of[k] = (support, sub, sup, [n for n in near if not frequent[n]])
        return self.classes_of[key]

    def mass(self, x: str, y: str) -> float:
        """q(x, y)."""
        _, sub, sup, rest = self.explore(x)
        if self.config.proposal == "uniform":
            return 1 / (len(sub) + len(sup) + len(rest))
        masses = balanced_masses(len(sub), len(sup), len(rest), self.config.eta, self.config.rho)
        for m, c in zip(masses, (sub, sup, rest)):
            if y in c:
                return m / len(c)
        return 0.0

    def propose(self, x: str, r: random.Random) -> str:
        _, sub, sup, rest = self.explore(x)
        if self.config.proposal == "uniform":
            return r.choice(sorted([*sub, *sup, *rest]))
        a, b, _ = balanced_masses(len(sub), len(sup), len(rest), self.config.eta, self.config.rho)
        t = r.random()
        return r.choice(sub if t < a else sup if t < a + b else rest or sup or sub)

    def step(self, x: str, r: random.Random) -> tuple[str, str, float, float, float, bool]:
        if (self.config.lazy and r.random() < self.config.lazy) or not self.lattice.neighbors(x):
            return x, x, 1.0, 1.0, 1.0, False
        y = self.propose(x, r)
        self.explore(y, self.lattice.neighbors(x))
        q, back = self.mass(x, y), self.mass(y, x)
        a = alpha(self.utility(self.explore(x)[0]), self.utility(self.explore(y)[0]), q, back, self.config.eps1, self.config.k, self.delta_u)
        ok = r.random() < a
        return (y if ok else x), y, q, back, a, ok

    def start(self, r: random.Random) -> str:
        """D9. The given pattern, or one of the least size of declared labels, without reading data (or any that is left)."""
        rules, gone = self.config.rules, self.lattice.removed
        if self.config.start is not None and self.config.start not in gone:
            return self.config.start
        labels = sorted(rules.labels)
        least = [f"{a}|" for a in labels] if rules.min_edges == 0 else [f"{a},{b}|0-1" for a in labels for b in labels if a <= b]
        least = [k for k in least if k not in gone and rules.allows(parse_key(k))]
        return r.choice(least or [k for k in enumerate_space(rules) if k not in gone])

    def chain(self, number: int, r: random.Random) -> tuple[str, int, list[tuple]]:
        """D11, D13. One sample of a converged chain; fails closed if it doesn't converge."""
        x, test, trace = self.start(r), Convergence(), []
        for step in range(1, self.config.max_steps + 1):
            at, (x, y, q, back, a, ok) = x, self.step(x, r)
            _, sub, sup, rest = self.explore(x)
            values = (len(sub) + len(sup) + len(rest), len(sub) + len(sup), x.count(",", 0, x.index("|")) + 1)
            trace.append((number, step, at, y, q, back, a, ok, *values, *test.z))
            if test.add(values) and step >= self.config.min_steps:
                return x, step, trace
        raise NotConverged(f"chain {number} didn't converge in {self.config.max_steps} steps; nothing is released")


def laplace_quantile(u: float, scale: float) -> float:
    """E1. The inverse distribution function, at u - 0.5 for u uniform in (-0.5, 0.5)."""
    return math.copysign(-scale * math.log(max(1e-300, 1 - 2 * abs(u))), u)


def laplace(r: random.Random, scale: float) -> float:
    return laplace_quantile(r.random() - 0.5, scale)


def bernoulli_exp(r: random.Random, num: int, den: int) -> bool:
    """True with probability exp(-num / den) for num <= den, by whole numbers only."""
    k = 1
    while r.randrange(den * k) < num:
        k += 1
    return k % 2 == 1


def discrete_laplace(r: random.Random, scale: float) -> int:
    """E1 for counts: whole-number noise with weights exp(-|n| / scale), drawn without floating point, whose gaps leak."""
    t, s = Fraction(scale).limit_denominator(1 << 20).as_integer_ratio()
    while True:
        u = r.randrange(t)
        if not bernoulli_exp(r, u, t):
            continue
        v = 0
        while bernoulli_exp(r, 1, 1):
            v += 1
        size, minus = (u + t * v) // s, r.randrange(2)
        if size or not minus:
            return -size if minus else size


NOISES = {"laplace": laplace, "discrete": discrete_laplace}


def sample_private_patterns(service, config: WalkConfig) -> Release:
    """E3. k patterns, each the sample of a chain over the space without those before; E5 adds noise to supports."""
    if config.k < 1 or config.eps1 <= 0 or (config.eps2 is not None and config.eps2 <= 0) or not 0 < config.eta <= 1 or not 0 <= config.rho <= 1 or config.contribution < 1:
        raise ValueError("k, eps1, eps2, eta, rho or contribution out of range")
    r, walker, ledger = config.randomness(), Walker(service, config), BudgetLedger()
    release = Release([], [], ledger)
    for number in range(1, config.k + 1):
        began = time.perf_counter()
        key, n, own = walker.chain(number, r)
        support = walker.explore(key)[0]
        release.patterns.append(key)
        release.steps.append(n)
        release.trace += own
        release.noisy.append(float(support + NOISES[config.noise](r, config.contribution * config.k / config.eps2)) if config.eps2 else None)
        release.seconds.append(time.perf_counter() - began)
        walker.lattice.remove(key)
        walker.classes_of.clear()
    ledger.spend("sampling", config.eps1)
    if config.eps2:
        ledger.spend("supports", config.eps2)
    ledger.away(config.k, config.eps1, config.theta)
    if config.f_source != "given":
        ledger.spend(f"threshold: {config.f_source}, not accounted for", 0.0)
    return release


# ---- exact laws for small spaces: D8, E2, E6-E8, E11-E14, F4, F5 ----
def transition_matrix(walker: Walker, space: list[str]):
    """D8. Row-stochastic matrix of one chain step over an enumerated space."""
    import numpy as np

    at, out = {k: i for i, k in enumerate(space)}, np.zeros((len(space), len(space)))
    for x in space:
        for y in walker.lattice.neighbors(x):
            q = walker.mass(x, y)
            if q:
                a = alpha(walker.utility(walker.explore(x)[0]), walker.utility(walker.explore(y)[0]), q, walker.mass(y, x), walker.config.eps1, walker.config.k, walker.delta_u)
                out[at[x], at[y]] = q * a * (1 - walker.config.lazy)
        out[at[x], at[x]] = 1 - out[at[x]].sum()
    return out


def chain_distance(walker: Walker, space: list[str], steps: int) -> float:
    """E6. Distance of the law after so many steps, begun as the walk begins, from the limit; for spaces that fit the driver."""
    import numpy as np

    left = [k for k in space if k not in walker.lattice.removed]
    law = exponential_law([walker.utility(walker.explore(k)[0]) for k in left], walker.config.eps1, walker.config.k, walker.delta_u)
    least = min(k.count("-") for k in left)
    begins = [k == walker.config.start if walker.config.start else k.count("-") == least for k in left]
    now, matrix = np.array(begins, float) / sum(begins), transition_matrix(walker, left)
    for _ in range(steps):
        now = now @ matrix
    return tv_distance(now, law)


def exponential_law(utilities: list[float], eps: float, k: int, delta_u: float = 1.0) -> list[float]:
    """E2. The exponential mechanism's distribution at budget eps / k; utilities of the whole space, patterns of support 0 too."""
    top = max(utilities)
    w = [math.exp(eps * (u - top) / (2 * k * delta_u)) for u in utilities]
    total = sum(w)
    return [x / total for x in w]


def exponential_probs(space: list[str], supports: dict[str, int], eps: float, k: int, score: str = "linear", f: int = 1) -> dict[str, float]:
    """E2. The probability of each pattern of a declared space, whether or not it occurs."""
    u, d = SCORES[score](f)
    return dict(zip(space, exponential_law([u(supports.get(x, 0)) for x in space], eps, k, d), strict=True))


def sample_exact_exponential(space: list[str], supports: dict[str, int], k: int, eps: float, r: random.Random, score: str = "linear", f: int = 1) -> list[str]:
    """F4. k draws without replacement, by the largest of Gumbel-perturbed scores."""
    u, d = SCORES[score](f)
    noisy = [(eps * u(supports.get(x, 0)) / (2 * k * d) - math.log(-math.log(r.random() or 1e-300)), x) for x in space]
    return [x for _, x in sorted(noisy, reverse=True)[:k]]


def laplace_all(space: list[str], supports: dict[str, int], k: int, eps: float, noise: Callable[[str, float], float]) -> list[tuple[str, float]]:
    """F5. Noise of scale |space| / eps on every support of the space, then the k largest, ties by key.

    noise(key, scale): what is added to a pattern's support.
    """
    noisy = [(x, supports.get(x, 0) + noise(x, len(space) / eps)) for x in space]
    return sorted(noisy, key=lambda t: (-t[1], t[0]))[:k]


def tv_distance(p: list[float], q: list[float]) -> float:
    return float(sum(abs(a - b) for a, b in zip(p, q)) / 2)


def tv_between(p: dict[str, float], q: dict[str, float]) -> float:
    """E7. Of two laws by pattern; a pattern that one of them lacks has probability 0 there."""
    every = sorted({*p, *q})
    return tv_distance([p.get(k, 0.0) for k in every], [q.get(k, 0.0) for k in every])


def tv_curve(matrix, law, start: int, steps: int) -> list[float]:
    """E8. Distance from the stationary law after each step."""
    import numpy as np

    x, out = np.eye(len(law))[start], []
    for _ in range(steps):
        x = x @ matrix
        out.append(float(np.abs(x - law).sum() / 2))
    return out


def delta_for(theta: float, eps1: float, k: int) -> float:
    return theta * (1 + math.exp(eps1 / k))


def utility_beta(k: int, eps1: float, gamma: float, space: int) -> float:
    """E11. All outputs have support above f - beta with probability 1 - gamma (linear score)."""
    return 2 * k / eps1 * (math.log(k / gamma) + math.log(space))


def noise_beta(k: int, eps2: float, gamma: float, together: bool = False) -> float:
    """E13. Bound of the noise of one support, or of all k at once."""
    return k / eps2 * math.log((k if together else 1) / gamma)


def sound(out: list[str], supports: dict[str, int], f: int, beta: float) -> bool:
    """E11. Whether all outputs have support above f - beta."""
    return all(supports.get(o, 0) > f - beta for o in out)


def complete(out: list[str], supports: dict[str, int], f: int, beta: float) -> bool:
    """E12. Whether all patterns of support above f + beta are among the outputs.

    The same beta as for soundness: if such a pattern is missing, some output of support at most f was drawn while it was
    there, which the exponential mechanism does with probability gamma at most.
    """
    return {p for p, s in supports.items() if s > f + beta} <= set(out)


def frequency_form(supports: dict[str, float], graphs: int) -> dict[str, float]:
    """E14. Supports, noisy or not, as shares of the (public) number of graphs; noise of scale k / eps2 becomes k / (eps2 n)."""
    return {p: s / graphs for p, s in supports.items()}


# ---- G1-G4 ----
def metrics(out: list[str], supports: dict[str, int], k: int) -> dict[str, float]:
    best = sorted(supports.items(), key=lambda t: (-t[1], t[0]))[:k]
    f = best[-1][1] if best else 1
    strict = len({b[0] for b in best} & set(out)) / k
    rse = (sum(s for _, s in best) - sum(supports.get(o, 0) for o in out)) / k / max(1, f)
    return {"precision": strict, "precision_ties": sum(supports.get(o, 0) >= f for o in out) / k, "rse": rse, "support_accuracy": 1 - rse, "false_negative_rate": 1 - strict}
