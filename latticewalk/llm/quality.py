"""Quality of documents by a generalised additive model with pairwise interactions.

Boosting goes round the features; each turn fits a shallow tree to one feature's binned gradients and adds
it to that feature's lookup table. Pairs of features with the largest remaining gain get tables of their own.
A score is the sigmoid of a sum of table entries, read for a whole batch at once.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from latticewalk.llm.common import held_out

FEATURES = ("log_chars", "log_words", "word_length", "long_words", "upper", "digits", "marks", "bars", "exclaims", "symbols", "lines", "distinct_words", "repeats", "top_word", "repeated_lines", "non_ascii", "line_words", "last_line", "marked_words", "pair_repeats")
_KIND = {name: np.array([chr(b) in set_ for b in range(256)]) for name, set_ in {"digits": "0123456789", "marks": ".,;:?'\"()-", "bars": "|", "exclaims": "!", "symbols": "#$%&*@<>{}[]^~=+_\\/`"}.items()}


def text_features(text: str | None) -> list[float]:
    """FEATURES of a whole text; all zero for null and empty ones."""
    if not text:
        return [0.0] * len(FEATURES)
    counts = np.bincount(np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8), minlength=256)
    n_bytes = int(counts.sum())
    share = {k: float(counts[v].sum()) / n_bytes for k, v in _KIND.items()}
    upper, lower = int(counts[65:91].sum()), int(counts[97:123].sum())
    words = text.split()
    n = len(words)
    if not n:
        return [float(np.log1p(len(text))), *[0.0] * (len(FEATURES) - 1)]
    lines = [x for x in text.split("\n") if x.strip()]
    held = Counter(words)
    repeats = sum(map(str.__eq__, words, words[1:]))
    letters = len(text) - text.count(" ")
    marked = sum(not w[-1].isalnum() for w in words) / n
    pairs = len(set(zip(words, words[1:]))) if n > 1 else 1
    return [
        float(np.log1p(len(text))), float(np.log1p(n)), letters / n, sum(len(w) > 12 for w in words) / n,
        upper / max(1, upper + lower), share["digits"], share["marks"], share["bars"], share["exclaims"], share["symbols"],
        len(lines) / n, len(held) / n, repeats / n, held.most_common(1)[0][1] / n, 1 - len(set(lines)) / max(1, len(lines)),
        float(counts[128:].sum()) / n_bytes, float(np.log1p(n / max(1, len(lines)))), len(lines[-1].split()) / n if lines else 0.0, marked, 1 - pairs / max(1, n - 1),
    ]


class AdditiveModel:
    """Lookup tables of single features and of pairs."""

    def __init__(self, bins: int = 48, rounds: int = 120, pair_bins: int = 8, pairs: int = 8, pair_rounds: int = 40, rate: float = 0.12, leaves: int = 4, ridge: float = 4.0):
        self.bins, self.rounds, self.pair_bins, self.n_pairs, self.pair_rounds, self.rate, self.leaves, self.ridge = bins, rounds, pair_bins, pairs, pair_rounds, rate, leaves, ridge

    def binned(self, x: np.ndarray, edges: list[np.ndarray]) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, j], side="right") for j, e in enumerate(edges)], axis=1) if len(x) else np.zeros((0, len(edges)), int)

    def fit(self, x: np.ndarray, y: np.ndarray) -> AdditiveModel:
        quantiles = lambda k: [np.unique(np.quantile(x[:, j], np.linspace(0, 1, k + 1)[1:-1])) for j in range(x.shape[1])]
        if not len(x):
            x = np.zeros((1, len(FEATURES)))
            y = np.array([1.0])
        self.edges, self.coarse = quantiles(self.bins), quantiles(self.pair_bins)
        b = self.binned(x, self.edges)
        self.bias = float(np.log((y.sum() + 1) / (len(y) - y.sum() + 1)))
        self.tables = [np.zeros(len(e) + 1) for e in self.edges]
        z = np.full(len(y), self.bias)
        for _ in range(self.rounds):
            for j, table in enumerate(self.tables):
                p = 1 / (1 + np.exp(-z))
                g, h = np.bincount(b[:, j], y - p, len(table)), np.bincount(b[:, j], p * (1 - p), len(table))
                step = self.rate * self.tree(g, h)
                table += step
                z += step[b[:, j]]
        self.pairs, self.pair_tables = [], []
        c = self.binned(x, self.coarse)
        p = 1 / (1 + np.exp(-z))
        gains = []
        for i in range(c.shape[1]):
            for j in range(i):
                g, h = self.grid(c, i, j, y - p), self.grid(c, i, j, p * (1 - p))
                gains.append((self.cross_gain(g, h), j, i))
        for _, j, i in sorted(gains, reverse=True)[: self.n_pairs]:
            self.pairs.append((j, i))
            self.pair_tables.append(np.zeros((len(self.coarse[j]) + 1, len(self.coarse[i]) + 1)))
        for _ in range(self.pair_rounds):
            for (j, i), table in zip(self.pairs, self.pair_tables, strict=True):
                p = 1 / (1 + np.exp(-z))
                g, h = self.grid(c, i, j, y - p).T, self.grid(c, i, j, p * (1 - p)).T
                rows = self.tree(g.sum(1), h.sum(1), 2)  # a cut of one feature, then one of the other on each side
                step = np.zeros_like(table)
                for value in np.unique(rows):
                    own = rows == value
                    step[own] = self.rate * self.tree(g[own].sum(0), h[own].sum(0), 2)
                table += step
                z += step[c[:, j], c[:, i]]
        return self

    def grid(self, c: np.ndarray, i: int, j: int, w: np.ndarray) -> np.ndarray:
        n, m = len(self.coarse[i]) + 1, len(self.coarse[j]) + 1
        return np.bincount(c[:, i] * m + c[:, j], w, n * m).reshape(n, m)

    def cross_gain(self, g: np.ndarray, h: np.ndarray) -> float:
        """Best gain of cutting both features once, over cutting neither."""
        gs, hs = g.cumsum(0).cumsum(1), h.cumsum(0).cumsum(1)
        parts = lambda s: (s, s[-1:, :] - s, s[:, -1:] - s, s[-1, -1] - s[-1:, :] - s[:, -1:] + s)
        return float(sum(a * a / (b + self.ridge) for a, b in zip(parts(gs), parts(hs), strict=True)).max())

    def tree(self, g: np.ndarray, h: np.ndarray, leaves: int | None = None) -> np.ndarray:
        """Leaf values by bin of a tree on binned gradients, grown by the best cut."""
        cuts = [(0, len(g))]
        for _ in range((leaves or self.leaves) - 1):
            best = None
            for k, (lo, hi) in enumerate(cuts):
                if hi - lo < 2:
                    continue
                gl, hl = g[lo:hi].cumsum(), h[lo:hi].cumsum()
                gain = gl[:-1] ** 2 / (hl[:-1] + self.ridge) + (gl[-1] - gl[:-1]) ** 2 / (hl[-1] - hl[:-1] + self.ridge) - gl[-1] ** 2 / (hl[-1] + self.ridge)
                at = int(gain.argmax())
                if best is None or gain[at] > best[0]:
                    best = (gain[at], k, lo + at + 1)
            if best is None or best[0] <= 1e-9:
                break
            lo, hi = cuts[best[1]]
            cuts[best[1] : best[1] + 1] = [(lo, best[2]), (best[2], hi)]
        out = np.zeros(len(g))
        for lo, hi in cuts:
            out[lo:hi] = g[lo:hi].sum() / (h[lo:hi].sum() + self.ridge)
        return out

    def scores(self, x: np.ndarray) -> np.ndarray:
        z = np.full(len(x), self.bias)
        for table, bin_ in zip(self.tables, self.binned(x, self.edges).T, strict=True):
            z += table[bin_]
        c = self.binned(x, self.coarse)
        for (j, i), table in zip(self.pairs, self.pair_tables, strict=True):
            z += table[c[:, j], c[:, i]]
        return 1 / (1 + np.exp(-z))


def with_features(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for batch in batches:
        yield batch.drop(columns="text").assign(x=[text_features(t if isinstance(t, str) else None) for t in batch["text"]])


def train(docs: DataFrame, labels: DataFrame, rows: int = 20_000) -> AdditiveModel:
    """Fit on at most `rows` labelled documents outside the test fold: those with the smallest hash of the id.

    The bound makes what the driver gets, and the broadcast of ids, fixed in size: of rows that repeat a chosen id at
    most `rows` more are taken, those with the smallest hash of the text. Labels that are null are left out; of
    contradicting labels of an id the larger holds. Without labels every score is a constant.
    """
    chosen = labels.where("quality is not null and doc_id is not null").where(~held_out())
    chosen = chosen.groupBy("doc_id").agg(F.max("quality").alias("label")).withColumn("h", F.xxhash64("doc_id")).orderBy("h", "doc_id").limit(rows).select("doc_id", "label")
    own = docs.selectExpr("cast(doc_id as long) doc_id", "text", "xxhash64(text) h").join(F.broadcast(chosen), "doc_id")
    found = own.mapInPandas(with_features, "doc_id long, h long, label int, x array<double>").orderBy("doc_id", "h").limit(2 * rows).toPandas()
    x = np.stack(found["x"]) if len(found) else np.zeros((0, len(FEATURES)))
    return AdditiveModel().fit(x, found["label"].to_numpy(float))


def score_documents(docs: DataFrame, model: AdditiveModel, threshold: float = 0.3) -> DataFrame:
    """The columns of docs with score and predicted (replacing columns of these names), a row for each row.

    score is 0 to 1, higher where label 1 is likelier, from the text alone; null and empty texts are scored
    as texts without any words. predicted is 1 from the threshold on.
    """
    @F.pandas_udf("double")
    def score(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for part in parts:
            x = np.array([text_features(t if isinstance(t, str) else None) for t in part]).reshape(len(part), len(FEATURES))
            yield pd.Series(model.scores(x))

    return docs.drop("score", "predicted").withColumn("score", score("text")).withColumn("predicted", (F.col("score") >= threshold).cast("int"))
