"""Chroma fingerprints of recordings, and their alignment.

Frames of a recording become energies of twelve pitch classes. Sixteen rectangle filters over sixteen frames,
read from an integral image, are quantised to two bits each and packed into a 32-bit code per frame. Anchors
are runs of four codes, chosen by local minima of their hash, so that recordings with a common stretch share
anchors in it. A histogram of the offsets of shared anchors gives the shifts of a pair, and the bit errors of all
overlapping codes measure each. All recordings that share an anchor are compared: in small groups pair by pair, in
large ones in pairs of blocks, each pair under the smallest anchor that it shares.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SPAN, RUN, REACH = 16, 4, 16
#: Filters (kind, lowest pitch class, height, width) by rule: five kinds over growing rectangles.
FILTERS = [(i % 5, (i * 5) % 7, 3 + i % 4, (4, 8, 12, 16)[i % 4]) for i in range(16)]
LEVELS = (-0.12, 0.0, 0.12)


def pitch_basis(window: int, rate: int) -> np.ndarray:
    """Complex sinusoids of the pitches below half the rate that the window can tell, by pitch class (12, pitches, window)."""
    lowest = 2.0 * rate / window
    octaves = max(1, int(np.log2(rate / 2 / lowest)))
    f = lowest * 2.0 ** (np.arange(12)[:, None] / 12 + np.arange(octaves)[None, :])
    t = np.arange(window) / rate
    return (np.hanning(window) * np.exp(-2j * np.pi * f[..., None] * t)).reshape(-1, window)


def n_frames(samples: int, window: int, hop: int) -> int:
    """Frames of a recording; one that is shorter than a window is padded to one."""
    return max(1, (samples - window) // hop + 1)


def energies(windows: np.ndarray, basis: np.ndarray) -> np.ndarray:
    """Energies of twelve pitch classes for each window of samples, scaled to unit length; silence is all zero."""
    both = np.concatenate([basis.real, basis.imag]).astype(np.float32).T
    w, k = windows @ both, both.shape[1] // 2
    out = (w[:, :k] ** 2 + w[:, k:] ** 2).reshape(len(w), 12, -1).sum(axis=2)
    size = np.sqrt((out * out).sum(axis=1, keepdims=True))
    return np.divide(out, size, out=np.zeros_like(out), where=size > 1e-6)


def chroma(recordings: list[np.ndarray], window: int, hop: int, basis: np.ndarray) -> list[np.ndarray]:
    """Frames of each recording (samples), all at once; windows are looked at in pieces, so long ones take bounded memory."""
    counts = [n_frames(len(x), window, hop) for x in recordings]
    sizes = [max(len(x), window) for x in recordings]
    track, at = np.zeros(sum(sizes), np.float32), np.concatenate([[0], np.cumsum(sizes)])
    for x, start in zip(recordings, at):
        track[start : start + len(x)] = x
    starts = np.concatenate([start + hop * np.arange(n) for n, start in zip(counts, at)])
    view = np.lib.stride_tricks.sliding_window_view(track, window)
    out = np.concatenate([energies(view[starts[i : i + 4096]], basis) for i in range(0, len(starts), 4096)])
    return np.split(out, np.cumsum(counts)[:-1])


#: Energies are whole numbers of these parts in the integral image, so that codes don't depend on what lies before.
PARTS = 1 << 16


def codes(recordings: list[np.ndarray]) -> list[np.ndarray]:
    """Packed codes of each recording (frames), one for each stretch of SPAN frames; short ones end in silence."""
    counts = [max(len(x), SPAN + RUN - 1) for x in recordings]
    at = np.concatenate([[0], np.cumsum(counts)])
    track = np.zeros((int(at[-1]), 12), np.int64)
    for x, start in zip(recordings, at):
        track[start : start + len(x)] = np.rint(x * PARTS)
    image = np.zeros((len(track) + 1, 13), np.int64)
    image[1:, 1:] = track.cumsum(0).cumsum(1)
    n = len(track) - SPAN + 1
    out = np.zeros(n, dtype=np.uint32)

    def area(t0: int, t1: int, p0: int, p1: int) -> np.ndarray:
        return image[t1 : t1 + n, p1] - image[t0 : t0 + n, p1] - image[t1 : t1 + n, p0] + image[t0 : t0 + n, p0]

    for number, (kind, p, height, width) in enumerate(FILTERS):
        q, m, w = p + height, p + height // 2, width // 2
        if kind == 0:  # earlier against later
            a, b = area(0, w, p, q), area(w, width, p, q)
        elif kind == 1:  # lower against higher
            a, b = area(0, width, p, m), area(0, width, m, q)
        elif kind == 2:  # one diagonal against the other
            a, b = area(0, w, p, m) + area(w, width, m, q), area(0, w, m, q) + area(w, width, p, m)
        elif kind == 3:  # the middle in time against both ends
            a, b = area(width // 4, width - width // 4, p, q), area(0, width // 4, p, q) + area(width - width // 4, width, p, q)
        else:  # the middle in pitch against both sides
            a, b = area(0, width, p + height // 3, q - height // 3), area(0, width, p, p + height // 3) + area(0, width, q - height // 3, q)
        x = np.log((PARTS + a) / (PARTS + b))
        level = (x > LEVELS[0]).astype(np.uint32) + (x > LEVELS[1]) + (x > LEVELS[2])
        out |= (level ^ (level >> 1)) << np.uint32(2 * number)  # neighbouring levels differ in one bit
    return [out[start : start + c - SPAN + 1] for start, c in zip(at, counts)]


def anchors(c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Keys and positions of runs of RUN codes whose hash is smallest within REACH: any long common stretch shares one."""
    n = len(c) - RUN + 1
    h = np.zeros(n, dtype=np.uint64)
    for i in range(RUN):
        h = (h ^ c[i : i + n].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
    if n <= REACH:
        at = np.array([int(h.argmin())])
    else:
        windows = np.lib.stride_tricks.sliding_window_view(h, REACH)
        at = np.unique(windows.argmin(axis=1) + np.arange(len(windows)))
    return h[at].view(np.int64), at


def bit_errors(a: np.ndarray, b: np.ndarray, offset: int) -> tuple[int, int]:
    """Overlapping codes when b's start is `offset` frames into a, and the bits in which they differ."""
    lo, hi = max(0, offset), min(len(a), len(b) + offset)
    if hi <= lo:
        return 0, 0
    return hi - lo, int(np.bitwise_count(a[lo:hi] ^ b[lo - offset : hi - offset]).sum())


def fingerprints(media: DataFrame, window: int = 128, hop: int = 32, rate: int = 8000) -> DataFrame:
    """id, n_frames, n_codes, codes (little-endian 32-bit) and anchors of recordings (id long, audio binary: unsigned 8-bit mono).

    Null and empty audio has no frames and no codes.
    """

    @F.pandas_udf("n_frames int, n_codes int, codes binary, anchors array<struct<key: bigint, at: int>>")
    def read(parts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        basis = pitch_basis(window, rate)
        for part in parts:
            rows: list[tuple] = [(0, 0, b"", [])] * len(part)
            for some in together(part, 1 << 20):
                tracks = [(np.frombuffer(part.iloc[i], np.uint8).astype(np.float32) - 128) / 128 for i in some]
                frames = chroma(tracks, window, hop, basis)
                for i, f, c in zip(some, frames, codes(frames), strict=True):
                    keys, at = anchors(c)
                    found = [{"key": k, "at": p} for k, p in zip(keys.tolist(), at.tolist(), strict=True)]
                    rows[i] = len(f), len(c), c.astype("<u4").tobytes(), found
            yield pd.DataFrame(rows, columns=["n_frames", "n_codes", "codes", "anchors"])

    return media.select("id", read("audio").alias("f")).select("id", "f.*")


def together(part: pd.Series, most: int) -> Iterator[list[int]]:
    """Places of recordings that aren't empty, in groups of at most `most` samples (or one recording)."""
    some, size = [], 0
    for i, raw in enumerate(part):
        if raw is None or not len(raw):
            continue
        if some and size + len(raw) > most:
            yield some
            some, size = [], 0
        some.append(i)
        size += len(raw)
    if some:
        yield some


class Print:
    """Codes of a recording with the positions of its anchors by key."""

    def __init__(self, raw: bytes):
        self.codes = np.frombuffer(raw, "<u4")
        self.places: dict[int, list[int]] = {}
        for key, at in zip(*(x.tolist() for x in anchors(self.codes)), strict=True):
            self.places.setdefault(key, []).append(at)


def votes(a: Print, b: Print, keys: set[int]) -> list[tuple[int, int]]:
    """Offsets of b's start into a that anchors of `keys` give, with their number: most first, ties by offset."""
    most = sum(len(a.places[k]) * len(b.places[k]) for k in keys)
    if most == 1:
        (key,) = keys
        return [(a.places[key][0] - b.places[key][0], 1)]
    if most <= 64:
        n: dict[int, int] = {}
        for key in keys:
            for p in a.places[key]:
                for q in b.places[key]:
                    n[p - q] = n.get(p - q, 0) + 1
        return sorted(n.items(), key=lambda x: (-x[1], x[0]))
    out = np.zeros(len(a.codes) + len(b.codes) + 1, np.int64)
    for key in keys:
        x, y = np.array(a.places[key]), np.array(b.places[key])
        if len(x) < len(y):
            for p in x:
                out[p - y + len(b.codes)] += 1
        else:
            for p in y:
                out[x - p + len(b.codes)] += 1
    at = np.flatnonzero(out)
    at = at[np.argsort(-out[at], kind="stable")]
    return list(zip((at - len(b.codes)).tolist(), out[at].tolist(), strict=True))


def verified(a: Print, b: Print, keys: set[int], worst: float) -> tuple[int, int, int, int] | None:
    """offset, votes, overlap and errors of the most voted offset (ties: the smaller) that passes, of all that have a vote."""
    for offset, n in votes(a, b, keys):
        overlap, errors = bit_errors(a.codes, b.codes, offset)
        if errors <= 32 * worst * overlap:
            return offset, n, overlap, errors
    return None


PART = "id long, links long, match_id long, match_offset int, votes int, overlap int, errors int, joined array<bigint>"


class Found:
    """Links of some pairs, added up by recording: rows of PART. joined are links that connect all that the pairs do."""

    def __init__(self):
        self.links: dict[int, int] = {}
        self.best: dict[int, tuple[int, int, tuple]] = {}
        self.joined: dict[int, list[int]] = {}
        self.parent: dict[int, int] = {}

    def root(self, x: int) -> int:
        while self.parent.get(x, x) != x:
            self.parent[x] = self.parent.get(self.parent[x], self.parent[x])
            x = self.parent[x]
        return x

    def compare(self, small: tuple[int, int, Print], large: tuple[int, int, Print], key: int, worst: float) -> None:
        """Two recordings (id, copies, print), the smaller id first, of which `key` is an anchor of both."""
        (i, n, a), (j, m, b) = small, large
        keys = a.places.keys() & b.places.keys()
        if min(keys) != key:  # the pair is compared under its smallest key
            return
        found = verified(a, b, keys, worst)
        if not found:
            return
        self.links[i], self.links[j] = self.links.get(i, 0) + m, self.links.get(j, 0) + n
        self.best[j] = max(self.best.get(j, (0, 0, ())), (found[1], -i, found))
        u, v = self.root(i), self.root(j)
        if u != v:
            self.parent[max(u, v)] = min(u, v)
            self.joined.setdefault(j, []).append(i)

    def rows(self) -> pd.DataFrame:
        rows = []
        for id_, n in self.links.items():
            _, other, found = self.best.get(id_, (0, None, (None,) * 4))
            rows.append((id_, n, None if other is None else -other, *found, self.joined.get(id_, [])))
        out = pd.DataFrame(rows, columns=[c.split()[0] for c in PART.split(", ")])
        whole = ["match_id", "match_offset", "votes", "overlap", "errors"]
        return out.astype(dict.fromkeys(whole, "Int64"))


def pair_links(members: DataFrame, own: DataFrame, worst: float) -> DataFrame:
    """Links (PART) within groups (key, rep) that are small enough to write out their pairs."""
    pairs = members.join(members.select("key", F.col("rep").alias("other")), "key").where("rep < other").groupBy("rep", "other").agg(F.min("key").alias("key"))

    def check(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            found = Found()
            for key, i, j, n, m, x, y in zip(*(batch[c] for c in ("key", "rep", "other", "copies", "more", "codes", "with")), strict=True):
                found.compare((int(i), int(n), Print(x)), (int(j), int(m), Print(y)), int(key), worst)
            yield found.rows()

    with_ = own.select(F.col("rep").alias("other"), F.col("copies").alias("more"), F.col("codes").alias("with"))
    return pairs.join(own, "rep").join(with_, "other").mapInPandas(check, PART)


def block_pairs(members: DataFrame, own: DataFrame, worst: float, block: int) -> DataFrame:
    """Links (PART) within large groups (key, rep, n: members of the group): members are dealt to blocks of about `block`, and each pair of blocks is one group."""
    live = members.withColumn("blocks", F.ceil(F.col("n") / block)).withColumn("own", F.expr("pmod(xxhash64(rep), blocks)"))
    live = live.select("key", "rep", "own", F.expr("explode(transform(sequence(0L, blocks - 1), x -> named_struct('i', least(own, x), 'j', greatest(own, x)))) b")).select("key", "rep", "own", "b.i", "b.j")

    def resolve(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for rows in whole_groups(batches):
            prints = {rep: Print(raw) for rep, raw in zip(rows["rep"].tolist(), rows["codes"])}
            own_print = [(rep, n, prints[rep]) for rep, n in zip(rows["rep"].tolist(), rows["copies"].tolist())]
            key, i, j, part = (rows[c].to_numpy() for c in ("key", "i", "j", "own"))
            new = (np.diff(key) != 0) | (np.diff(i) != 0) | (np.diff(j) != 0)
            starts = [0, *(np.flatnonzero(new) + 1).tolist(), len(rows)]
            for start, end in zip(starts, starts[1:]):
                yield block_links(int(key[start]), bool(i[start] == j[start]), own_print[start:end], (part[start:end] == i[start]).tolist(), worst)

    # a number of parts is given, as pairs of blocks are small to send and long to compare, so they mustn't be put together
    on, parts = ("key", "i", "j"), int(live.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return live.join(own, "rep").repartition(parts, *on).sortWithinPartitions(*on, "rep").mapInPandas(resolve, PART)


def whole_groups(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Rows sorted by key, i and j in frames that hold groups whole: the last group of a batch waits for the next."""
    rest = None
    for batch in batches:
        rows = batch if rest is None else pd.concat([rest, batch], ignore_index=True)
        if not len(rows):
            continue
        last = rows.iloc[-1]
        done = ((rows["key"] != last["key"]) | (rows["i"] != last["i"]) | (rows["j"] != last["j"])).to_numpy()
        rest = rows[~done]
        if done.any():
            yield rows[done].reset_index(drop=True)
    if rest is not None and len(rest):
        yield rest.reset_index(drop=True)


def block_links(key: int, same: bool, own: list[tuple[int, int, Print]], left: list[bool], worst: float) -> pd.DataFrame:
    """Links (PART) of one pair of blocks, members in order of id: all pairs of one block (same), or of the left with the right one."""
    found = Found()
    for y, large in enumerate(own):
        for x in range(y):
            if same or left[x] != left[y]:
                found.compare(own[x], large, key, worst)
    return found.rows()


def align(media: DataFrame, worst: float = 0.2, small: int = 8, block: int = 256, **how) -> DataFrame:
    """id, n_frames, n_codes, codes_crc32, match_id, match_offset, votes, overlap, errors, class_id, links: a row for each recording.

    Two recordings that share an anchor are linked if at most `worst` of the overlapping bits differ at an offset that
    a shared anchor gives. All pairs that share an anchor are compared. class_id is the smallest id reachable over links,
    links counts the other ids linked with a recording, copies and larger ids among them. Of the smaller ids, match_id is
    the one with the most votes (shared anchors at the offset; ties: smaller id), null where there is none.
    Recordings of equal codes are one for the search, and linked with each other and with what any of them is linked with.
    Recordings without codes, and rows with a null id, match nothing: class_id is the id. Of rows that repeat an id,
    each gets the id's match and own counts. An empty table gives no rows. Groups of an anchor with more than `small`
    recordings are compared in blocks of about `block`; neither changes rows.
    """
    from latticewalk.llm.common import cut
    from latticewalk.llm.near_dups import components

    keys = F.array_distinct("anchors.key").alias("keys")
    prints = fingerprints(media, **how).select("id", "n_frames", "n_codes", "codes", keys, F.size("anchors").alias("n_anchors"))
    prints = cut(prints.withColumn("same", F.unhex(F.sha2("codes", 256))))
    ids = prints.where("id is not null and n_codes > 0").groupBy("id").agg(F.max(F.struct("same", "n_codes", "n_anchors")).alias("p")).select("id", "p.*")
    classes = cut(ids.groupBy("same").agg(F.min("id").alias("rep"), F.count("*").alias("copies")))
    reps = prints.join(classes, (F.col("id") == F.col("rep")) & (prints["same"] == classes["same"])).select("rep", "copies", "codes", "keys").dropDuplicates(["rep"])
    spots = reps.select("rep", F.explode("keys").alias("key"))
    shared = spots.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    members = cut(spots.join(shared, "key"))
    own = cut(reps.select("rep", "copies", "codes").join(members.select("rep").distinct(), "rep", "left_semi"))
    parts = pair_links(members.where(F.col("n") <= small).select("key", "rep"), own, worst)
    parts = cut(parts.unionByName(block_pairs(members.where(F.col("n") > small), own, worst, block)))
    root = components(parts.select(F.col("id").alias("u"), F.explode("joined").alias("v")))
    linked = F.when(F.col("match_id").isNotNull(), F.struct("votes", (-F.col("match_id")).alias("m"), (-F.col("match_offset")).alias("o"), "overlap", "errors"))
    best = parts.groupBy("id").agg(F.max(linked).alias("b"), F.sum("links").alias("found"))
    copies = ids.join(classes, "same").join(best.withColumnRenamed("id", "rep"), "rep", "left").join(root.select(F.col("node").alias("rep"), F.col("root").alias("label")), "rep", "left")
    first = F.struct(F.col("n_anchors").alias("votes"), (-F.col("rep")).alias("m"), F.lit(0).alias("o"), F.col("n_codes").alias("overlap"), F.lit(0).alias("errors"))
    copies = copies.withColumn("b", F.when(F.col("id") == F.col("rep"), F.col("b")).otherwise(F.greatest("b", first)))
    # the smallest id of a class is the first of its own copies, as rep is the smallest id of each
    found = copies.select("id", (-F.col("b.m")).alias("match_id"), (-F.col("b.o")).alias("match_offset"), "b.votes", "b.overlap", "b.errors", F.coalesce("label", "rep").alias("class_id"), (F.coalesce("found", F.lit(0)) + F.col("copies") - 1).alias("links"))
    out = prints.select("id", "n_frames", "n_codes", F.crc32("codes").alias("codes_crc32")).join(found, "id", "left")
    return out.withColumn("class_id", F.coalesce("class_id", "id")).withColumn("links", F.coalesce("links", F.lit(0)))
