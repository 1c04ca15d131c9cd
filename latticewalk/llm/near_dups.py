"""Near-duplicate documents by HyperMinHash sketches, banding, and exact confirmation.

A sketch has a register for each of 256 buckets of hash space: the leading zeros of the bucket's
smallest hash and ten bits of its mantissa, so a register is smaller than a whole minimum. Bands of
six registers propose candidates; the Jaccard estimate from equal registers, corrected for chance
collisions, drops candidates that are far off; the rest are confirmed on full sets of shingles.

Groups of a band are never expanded to all pairs. First every member is compared with the group's
smallest id, and components are found. In groups that are not one component by then, members outside
the largest component are compared with each other and with it, in blocks. So each pair that shares a
band is either compared or already connected, and thousands of copies need about as many comparisons.
Groups and blocks hold sketches; full sets are made and moved only for pairs whose estimate passes.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from latticewalk.llm.common import cut, trimmed

BUCKETS, BAND, MANTISSA = 256, 6, 10
BANDS = BUCKETS // BAND
EMPTY = 0xFFFF
_ODD = np.uint64(0x9E3779B97F4A7C15)
_POWER = np.uint64(0xD6E8FEB86659FD93)


def _mix(x: np.ndarray) -> np.ndarray:
    """A bijective mix of 64-bit integers."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_BYTE = _mix(np.arange(1, 257, dtype=np.uint64) * _ODD) | np.uint64(1)
_LOWER = np.array([b + 32 if 65 <= b <= 90 else b for b in range(256)], dtype=np.uint8)
_BLANK = np.array([b == 32 or 9 <= b <= 13 for b in range(256)])
#: The power and its inverse, to any power below 2**16, by repeated products.
_UP = np.cumprod(np.full(1 << 16, _POWER, dtype=np.uint64))
_UP = np.concatenate([[np.uint64(1)], _UP[:-1]])


def word_hashes(text: str) -> np.ndarray:
    """A 64-bit hash of each word (A-Z in lower case), by polynomial sums over the bytes of the whole text at once."""
    raw = _LOWER[np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)]
    blank = np.concatenate([[True], _BLANK[raw], [True]])
    edges = np.flatnonzero(blank[1:] != blank[:-1])
    starts, ends = edges[::2], edges[1::2]
    if not len(starts):
        return np.zeros(0, np.uint64)
    at = np.arange(len(raw)) - np.repeat(np.concatenate([[0], starts]), np.diff(np.concatenate([[0], starts, [len(raw)]])))
    values = _BYTE[raw] * (_UP[np.minimum(at, len(_UP) - 1)] if at.max() < len(_UP) else _powers(at))
    sums = np.concatenate([[np.uint64(0)], np.cumsum(values, dtype=np.uint64)])
    return _mix(sums[ends] - sums[starts] + (ends - starts).astype(np.uint64) * _ODD)


def _powers(at: np.ndarray) -> np.ndarray:
    step = np.uint64(pow(int(_POWER), len(_UP), 1 << 64))
    high = np.cumprod(np.concatenate([[np.uint64(1)], np.full(int(at.max()) // len(_UP), step, dtype=np.uint64)]))
    return _UP[at % len(_UP)] * high[at // len(_UP)]


def shingle_hashes(text: str | None, words: int) -> np.ndarray:
    """The set of `words`-word shingles as sorted distinct 64-bit hashes; fewer words are one shingle, none are no set."""
    h = word_hashes(text) if text else np.zeros(0, np.uint64)
    if not len(h):
        return h
    n = min(words, len(h))
    out = np.full(len(h) - n + 1, n, dtype=np.uint64)
    for i in range(n):
        out = _mix(out * _POWER + h[i : len(h) - n + 1 + i])
    return np.unique(out)


def sketch(hashes: np.ndarray) -> np.ndarray:
    """Registers of sorted distinct hashes: leading zeros, then the bits after the first one; EMPTY where a bucket has none."""
    out = np.full(BUCKETS, EMPTY, dtype=np.uint16)
    bucket = (hashes >> np.uint64(56)).astype(np.int64)
    first = np.flatnonzero(np.diff(bucket, prepend=-1))
    low = hashes[first] << np.uint64(8) | np.uint64(255)
    exact = np.frexp((low >> np.uint64(11)).astype(np.float64))[1]  # 53 bits are exact
    zeros = 53 - exact
    mantissa = (low << (zeros + 1).astype(np.uint64)) >> np.uint64(64 - MANTISSA)
    out[bucket[first]] = (zeros.astype(np.uint64) << np.uint64(MANTISSA) | mantissa).astype(np.uint16)
    return out


#: For each bucket, the order in which it looks for a bucket to borrow from: a pseudo-random permutation of all.
_LOOK = np.argsort(_mix(np.arange(BUCKETS * BUCKETS, dtype=np.uint64) * _ODD).reshape(BUCKETS, BUCKETS), axis=1)


def densified(registers: np.ndarray) -> np.ndarray:
    """Registers for banding: an empty bucket borrows the first filled one in its own order.

    So each register of a short text, too, agrees with that of another text with probability of their similarity,
    and a band never rests on one shingle.
    """
    filled = registers != EMPTY
    if filled.all() or not filled.any():
        return registers
    out = registers.copy()
    look = _LOOK[~filled]
    out[~filled] = registers[look[np.arange(len(look)), filled[look].argmax(axis=1)]]
    return out


_HALVES = 2.0 ** -np.arange(65)


def cells(sizes: np.ndarray) -> np.ndarray:
    """For each set size, the chance that a bucket's minimum has 0, 1, ... leading zeros (a row each)."""
    upto = np.exp(-np.asarray(sizes, float)[:, None] / BUCKETS * _HALVES[None, :])
    return upto[:, 1:] - upto[:, :-1]


def chance(n: int, m: int) -> float:
    """Expected share of equal registers of two unrelated sets of n and m shingles: both minima fall in one cell."""
    a, b = cells(np.array([n, m]))
    return float(a @ b / 2**MANTISSA)


def passes(about: np.ndarray, registers: np.ndarray, percent: int) -> np.ndarray:
    """Whether an estimate that rests on so many registers is at most six standard errors below the threshold."""
    least = percent / 100
    return about + 6 * np.sqrt(least * (1 - least) / registers) >= least


def estimate(a: np.ndarray, b: np.ndarray, n: int, m: int) -> tuple[float, int]:
    """Jaccard similarity from two sketches, corrected for chance collisions, and the registers that it rests on."""
    used = (a != EMPTY) | (b != EMPTY)
    k = int(used.sum())
    if not k:
        return 0.0, 0
    equal, c = float((a[used] == b[used]).mean()), chance(n, m)
    return max(0.0, (equal - c) / (1 - c)), k


def components(edges: DataFrame) -> DataFrame:
    """Connected components of edges (u, v): node and the smallest node that it reaches.

    Large-star and small-star steps in turn: each links a node's neighbours to the smallest of them,
    which halves distances; only minima are aggregated, so hubs need no lists.
    """
    def star(e: DataFrame, small: bool) -> DataFrame:
        both = e if small else e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy(F.col("u").alias("w")).agg(F.least(F.min("v"), F.first("u")).alias("m"))
        near = both.join(least, F.col("u") == F.col("w"))
        if small:
            out = near.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(near.select("u", F.col("m").alias("v")))
        else:
            out = near.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        return out.where("u <> v").distinct()

    pairs = cut(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v").distinct())
    state = None
    while True:
        pairs = cut(star(star(pairs, False), True))
        now = pairs.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == state:
            break
        state = now
    return pairs.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("root"))


def signatures(docs: DataFrame, words: int) -> DataFrame:
    """doc_id, n_shingles, a key of the whole set, and its sketch."""

    @F.pandas_udf("n_shingles long, set_key binary, sketch binary")
    def sign(parts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for part in parts:
            rows = []
            for text in part:
                h = shingle_hashes(text if isinstance(text, str) else None, words)
                key = hashlib.blake2b(h.tobytes(), digest_size=16).digest()
                rows.append((len(h), key, sketch(h).tobytes() if len(h) else None))
            yield pd.DataFrame(rows, columns=["n_shingles", "set_key", "sketch"])

    return docs.select("doc_id", sign("text").alias("s")).select("doc_id", "s.*")


def registers_of(column: pd.Series) -> np.ndarray:
    return np.frombuffer(b"".join(column), np.uint16).reshape(len(column), BUCKETS)


def banded(registers: np.ndarray) -> np.ndarray:
    """Sketches (a row each) as bands of densified registers."""
    return np.stack([densified(r) for r in registers])[:, : BANDS * BAND].reshape(len(registers), BANDS, BAND)


#: Low bits of a band's key: its number.
BAND_BITS = 6


def band_rows(classes: DataFrame) -> DataFrame:
    """key (of a band's registers, with its number in the lowest bits), rep: a row for each band of each class (rep, sketch)."""

    def spread(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        number = np.arange(BANDS, dtype=np.uint64)
        for batch in batches:
            if not len(batch):
                continue
            bands = banded(registers_of(batch["sketch"])).astype(np.uint64)
            key = np.broadcast_to((number + np.uint64(1)) * _ODD, bands.shape[:2])
            for i in range(BAND):
                key = _mix((key ^ bands[:, :, i]) * _POWER + _ODD)
            key = key >> np.uint64(BAND_BITS) << np.uint64(BAND_BITS) | number
            yield pd.DataFrame({"key": key.reshape(-1).view(np.int64), "rep": np.repeat(batch["rep"].to_numpy(), BANDS)})

    return classes.select("rep", "sketch").mapInPandas(trimmed(spread), "key long, rep long")


def likely(pairs: DataFrame, classes: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose sizes allow a link and whose similarity, estimated and corrected for chance, isn't far below it."""
    side = lambda c: classes.select(F.col("rep").alias(c), F.col("n").alias(f"n_{c}"), F.col("sketch").alias(f"sketch_{c}"))

    def weigh(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            if not len(batch):
                continue
            x, y = registers_of(batch["sketch_a"]), registers_of(batch["sketch_b"])
            used = (x != EMPTY) | (y != EMPTY)
            k = used.sum(axis=1)
            by_chance = (cells(batch["n_a"]) * cells(batch["n_b"])).sum(axis=1) / 2**MANTISSA
            about = (((x == y) & used).sum(axis=1) / k - by_chance) / (1 - by_chance)
            yield batch[["a", "b"]][passes(about, k, percent)]

    both = pairs.select("a", "b").join(side("b"), "b").join(side("a"), "a").where(f"100 * least(n_a, n_b) >= {percent} * greatest(n_a, n_b)")
    return both.mapInPandas(trimmed(weigh), "a long, b long")


def full_sets(docs: DataFrame, reps: DataFrame, words: int) -> DataFrame:
    """rep and the full set of shingles, for the documents of reps (rep)."""

    def sets(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            yield pd.DataFrame({"rep": batch["rep"], "full": [shingle_hashes(t, words).tobytes() for t in batch["text"]]})

    reps = reps.select("rep").distinct()
    # an inner join, as the optimizer would push a semi join below the filter by the bitmap
    own = maybe_in(docs.selectExpr("cast(doc_id as long) rep", "text"), reps).join(reps, "rep")
    return own.dropDuplicates(["rep", "text"]).mapInPandas(trimmed(sets), "rep long, full binary")


#: Bits of the bitmap of ids, in parts of 4 kB: 4 MB, whatever the number of ids.
ID_BITS = 1 << 25


def maybe_in(rows: DataFrame, reps: DataFrame) -> DataFrame:
    """Rows whose rep may be one of reps: all that are, and some that aren't, the fewer the emptier the bitmap.

    So that texts that take no part aren't shuffled. The bitmap of hashed ids has a fixed size and is broadcast.
    """
    at = F.pmod(F.xxhash64("rep"), F.lit(ID_BITS))
    bits = reps.select(at.alias("at")).groupBy(F.expr("bitmap_bucket_number(at)").alias("__part"))
    bits = bits.agg(F.expr("bitmap_construct_agg(bitmap_bit_position(at))").alias("__bits"))
    known = rows.withColumn("at", at).selectExpr("*", "bitmap_bucket_number(at) __part", "bitmap_bit_position(at) __bit").join(F.broadcast(bits), "__part")
    byte = "conv(hex(substring(__bits, cast(__bit div 8 as int) + 1, 1)), 16, 10)"
    return known.where(f"(shiftright(cast({byte} as int), cast(__bit % 8 as int)) & 1) = 1").select(*rows.columns)


def confirm(pairs: DataFrame, docs: DataFrame, words: int, percent: int) -> DataFrame:
    """Of pairs (a, b, and what else they carry), those with 100 * intersection >= percent * union of their full sets."""
    reps = pairs.select(F.explode(F.array("a", "b")).alias("rep"))
    sets = cut(full_sets(docs, reps, words))
    side = lambda c: sets.select(F.col("rep").alias(c), F.col("full").alias(f"full_{c}"))
    columns = pairs.columns

    def check(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            linked = []
            for x, y in zip(batch["full_a"], batch["full_b"], strict=True):
                u, v = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                common = len(np.intersect1d(u, v, assume_unique=True))
                linked.append(100 * common >= percent * (len(u) + len(v) - common))
            yield batch[columns][np.array(linked, bool)]

    return pairs.join(side("b"), "b").join(side("a"), "a").mapInPandas(trimmed(check), pairs.schema)


def cross_blocks(members: DataFrame, block: int) -> DataFrame:
    """key, rep, label, own, is_main, i, j: members of groups that aren't one component yet, dealt to pairs of blocks.

    A group's members outside its largest component meet each other and that component, in blocks of bounded size:
    block i of the rest meets the blocks from its own on, and all blocks of the main component (negative numbers).
    """
    by_label = members.groupBy("key", "label").agg(F.count("*").alias("c"))
    groups = by_label.groupBy("key").agg(F.max_by("label", F.struct("c", "label")).alias("main"), F.max("c").alias("n_main"), (F.sum("c") - F.max("c")).alias("n_rest")).where("n_rest > 0")
    live = members.join(groups, "key").withColumn("is_main", F.col("label") == F.col("main"))
    live = live.withColumn("blocks", F.ceil(F.col("n_rest") / block)).withColumn("main_blocks", F.ceil(F.col("n_main") / block))
    live = live.withColumn("own", F.pmod(F.xxhash64("rep"), F.when(F.col("is_main"), F.col("main_blocks")).otherwise(F.col("blocks"))))
    later = "transform(sequence(own, blocks - 1), j -> named_struct('i', own, 'j', j))"
    earlier = "if(own > 0, transform(sequence(0L, own - 1), j -> named_struct('i', j, 'j', own)), array())"
    mains = "transform(sequence(1L, main_blocks), j -> named_struct('i', own, 'j', -j))"
    main = "transform(sequence(0L, blocks - 1), i -> named_struct('i', i, 'j', -own - 1))"
    return live.select("key", "rep", "label", "own", "is_main", F.expr(f"inline(if(is_main, {main}, concat({later}, {earlier}, {mains})))"))


class Blocks:
    """Members of pairs of blocks, sorted by key, i, j and rep: the pairs that may link different components, by estimate."""

    def __init__(self, rows: pd.DataFrame, percent: int):
        self.percent, self.plain = percent, registers_of(rows["sketch"])
        self.bands, self.size = banded(self.plain), rows["n"].to_numpy()
        self.cells, self.label, self.rep = cells(self.size), rows["label"].to_numpy(), rows["rep"].to_numpy()
        self.main, self.own = rows["is_main"].to_numpy(bool), rows["own"].to_numpy()
        self.key, self.i, self.j = (rows[c].to_numpy() for c in ("key", "i", "j"))
        new = (np.diff(self.key) != 0) | (np.diff(self.i) != 0) | (np.diff(self.j) != 0)
        self.starts = np.concatenate([[0], np.flatnonzero(new) + 1, [len(rows)]]).tolist()

    def sides(self, start: int, end: int) -> tuple[np.ndarray, np.ndarray, bool]:
        """Rows of the left block, those of the right one, and whether they are the same block."""
        i, j, here = self.i[start], self.j[start], slice(start, end)
        if i == j:
            return np.arange(start, end), np.arange(start, end), True
        left = ~self.main[here] & (self.own[here] == i)
        right = self.main[here] if j < 0 else ~self.main[here] & (self.own[here] == j)
        return start + np.flatnonzero(left), start + np.flatnonzero(right), False

    def pairs(self, start: int, end: int, most: int = 4_000) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """All pairs of a left with a right row, a bounded number at a time."""
        left, right, same = self.sides(start, end)
        step = max(1, most // max(1, len(right)))
        for at in range(0, len(left), step):
            some = left[at : at + step]
            a, b = np.repeat(some, len(right)), np.tile(right, len(some))
            yield (a[a < b], b[a < b]) if same else (a, b)

    def likely(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of pairs of rows those to compare, and their estimates.

        A pair is compared in the first band that it shares, and not if it is in one component already.
        """
        fits = 100 * np.minimum(self.size[a], self.size[b]) >= self.percent * np.maximum(self.size[a], self.size[b])
        keep = (self.label[a] != self.label[b]) & fits
        a, b = a[keep], b[keep]
        shared = (self.bands[a] == self.bands[b]).all(axis=2)
        keep = shared.any(axis=1) & (shared.argmax(axis=1) == self.key[a] & ((1 << BAND_BITS) - 1))
        a, b = a[keep], b[keep]
        used = (self.plain[a] != EMPTY) | (self.plain[b] != EMPTY)
        k = used.sum(axis=1)
        by_chance = (self.cells[a] * self.cells[b]).sum(axis=1) / 2**MANTISSA
        about = (((self.plain[a] == self.plain[b]) & used).sum(axis=1) / np.maximum(k, 1) - by_chance) / (1 - by_chance)
        keep = passes(about, np.maximum(k, 1), self.percent)
        return a[keep], b[keep], about[keep]

    def proposals(self, most: float) -> Iterator[pd.DataFrame]:
        """The pairs to confirm; a block pair with more than `most` of them a member is one row without a pair instead."""

        def frame(a: np.ndarray, b: np.ndarray, group: np.ndarray) -> pd.DataFrame:
            crowded = np.bincount(group, minlength=len(self.starts)) > most * np.diff([*self.starts, self.starts[-1]])
            where = np.flatnonzero(crowded)
            a, b = a[~crowded[group]], b[~crowded[group]]
            whole = pd.DataFrame({"key": self.key[a], "i": self.i[a], "j": self.j[a], "a": self.rep[a], "b": self.rep[b], "u": self.label[a], "v": self.label[b]})
            at = np.array(self.starts)[where]
            return pd.concat([whole, pd.DataFrame({"key": self.key[at], "i": self.i[at], "j": self.j[at]})]).astype("Int64")

        held, n = [], 0
        for g, (start, end) in enumerate(zip(self.starts, self.starts[1:])):
            found = 0
            for a, b in self.pairs(start, end):
                if len(a) > 500:  # many at once are looked at by themselves, and only until there are too many
                    a, b, _ = self.likely(a, b)
                    found += len(a)
                held.append((a, b))
                n += len(a)
                if found > most * (end - start):
                    break
            if n > 4_000 or g == len(self.starts) - 2:
                a, b = (np.concatenate(x) for x in zip(*held)) if held else [np.zeros(0, int)] * 2
                a, b, _ = self.likely(a, b)
                yield frame(a, b, np.searchsorted(np.array(self.starts), a, side="right") - 1)
                held, n = [], 0

    def links(self, full: list[np.ndarray]) -> list[tuple[int, int]]:
        """Links that join components, of one pair of blocks, with the full sets of its rows; likeliest first."""
        parent: dict[int, int] = {}

        def find(x: int) -> int:
            while parent.get(x, x) != x:
                parent[x] = parent.get(parent[x], parent[x])
                x = parent[x]
            return x

        out = []
        for a, b in self.pairs(0, len(full)):
            a, b, about = self.likely(a, b)
            for at in np.argsort(-about, kind="stable"):
                x, y = a[at], b[at]
                u, v = find(int(self.label[x])), find(int(self.label[y]))
                if u != v:
                    common = len(np.intersect1d(full[x], full[y], assume_unique=True))
                    if 100 * common >= self.percent * (len(full[x]) + len(full[y]) - common):
                        parent[max(u, v)] = min(u, v)
                        out.append((int(self.label[x]), int(self.label[y])))
        return out


def cross_links(members: DataFrame, classes: DataFrame, docs: DataFrame, words: int, percent: int, block: int = 512, most: float = 0.5) -> DataFrame:
    """Links (u, v) between the components (label) of members of one group: key, rep, label.

    Blocks hold sketches and give the pairs to confirm. A pair of blocks with more than `most` of them a member, such as
    those of a large group of texts that are all alike but not enough, is resolved in its own task with full sets
    instead, so that its pairs are never written out; of its links those are returned that join components.
    """
    live = cut(cross_blocks(members, block))
    sized = classes.select("rep", "n", "sketch")

    def propose(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rest = None
        for batch in batches:
            rows = batch if rest is None else pd.concat([rest, batch], ignore_index=True)
            last = rows.iloc[-1] if len(rows) else None
            if last is None:
                continue
            whole = ((rows["key"] != last["key"]) | (rows["i"] != last["i"]) | (rows["j"] != last["j"])).to_numpy()
            rest = rows[~whole]  # the last group may go on
            if whole.any():
                yield from Blocks(rows[whole].reset_index(drop=True), percent).proposals(most)
        if rest is not None and len(rest):
            yield from Blocks(rest.reset_index(drop=True), percent).proposals(most)

    def resolve(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("rep").reset_index(drop=True)
        links = Blocks(rows, percent).links([np.frombuffer(x, np.uint64) for x in rows["full"]])
        return pd.DataFrame(links, columns=["u", "v"], dtype="int64")

    on = ("key", "i", "j")
    dealt = live.join(sized, "rep").repartition(*on).sortWithinPartitions(*on, "rep")
    found = cut(dealt.mapInPandas(trimmed(propose), "key long, i long, j long, a long, b long, u long, v long"))
    links = confirm(found.where("a is not null").select("a", "b", "u", "v"), docs, words, percent).select("u", "v")
    crowded = found.where("a is null").select(*on)
    if crowded.isEmpty():
        return links
    rows = cut(live.join(crowded, [*on]))
    rows = rows.join(sized, "rep").join(cut(full_sets(docs, rows, words)), "rep")
    return links.unionByName(rows.groupBy(*on).applyInPandas(resolve, "u long, v long"))


def near_duplicates(docs: DataFrame, words: int = 5, percent: int = 80, **blocks) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable over links) and kept (doc_id = component_id), a row each.

    Links join documents with 100 * intersection >= percent * union of their shingle sets. Null and empty
    texts have no set and are linked with nothing. Rows with a null id take part in nothing: component_id is
    null and they are kept. Rows that repeat an id are one node; of rows repeated whole each comes back.
    Other columns are left out. An empty table gives no rows. blocks: sizes of cross_links; they don't change rows.
    """
    sig = cut(signatures(docs, words))
    classes = sig.where("n_shingles > 0 and doc_id is not null").groupBy("set_key").agg(F.min("doc_id").alias("rep"), F.min("n_shingles").alias("n"), F.first("sketch").alias("sketch"))
    classes = cut(classes)
    rows = band_rows(classes)
    shared = rows.groupBy("key").agg(F.min("rep").alias("a"), F.max("rep").alias("__hi")).where("a < __hi").drop("__hi")
    members = cut(rows.join(shared, "key"))
    # first each member of a band's group against the smallest id in it
    pairs = members.where("a <> rep").select("a", F.col("rep").alias("b")).distinct()
    near = confirm(cut(likely(pairs, classes, percent)), docs, words, percent)
    root = components(near.select(F.col("a").alias("u"), F.col("b").alias("v")))
    labels = members.select("rep").distinct().join(root, F.col("rep") == F.col("node"), "left").select("rep", F.coalesce("root", "rep").alias("label"))
    labels = cut(labels)
    # then, in groups that are not one component yet, members of different components against each other
    more = components(cross_links(members.select("key", "rep").join(labels, "rep"), classes, docs, words, percent, **blocks))
    labels = labels.join(more, F.col("label") == F.col("node"), "left").select("rep", F.coalesce("root", "label").alias("label"))
    by_class = classes.join(labels, "rep", "left").select("set_key", F.coalesce("label", "rep").alias("label"))
    out = sig.drop("sketch").join(by_class, "set_key", "left")
    component = F.when(F.col("n_shingles") > 0, F.coalesce("label", "doc_id")).otherwise(F.col("doc_id"))
    return out.select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), component).alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))
