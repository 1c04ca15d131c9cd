"""Packing of tokenised documents into sequences of a fixed size, by bin completion.

Documents are tokenised where they are read; only lengths are shuffled, in groups of bounded
size that are dealt out evenly. In each group best-fit decreasing gives the incumbent. Where it
needs more sequences than the lengths' sum does, a branch-and-bound search fills one sequence at
a time around the largest piece left, tries only undominated fillings, least waste first, and
leaves a branch once its waste excludes a better packing.
"""

from __future__ import annotations

import os
import re
import zlib
from bisect import bisect_right
from collections.abc import Iterator
from itertools import islice
from struct import pack as pack_ids

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame

from latticewalk.llm.common import cut, n_groups, once, trimmed
from latticewalk.llm.token_counts import TwoGenerations, byte_letters

#: Blanks are dropped by the word vocabulary, so a text may be encoded run by run.
RUNS = re.compile(r"[^ \n]+")
#: Letters that have one lower-case form and are composed already, and marks after them: two pieces to the vocabulary.
PLAIN = re.compile(r"([A-Za-zÀ-ÖØ-öø-ÿ]+)([!-&(-/:-@\[-`{-~]+)?\Z")


class WordEncoder:
    """Token ids of whole texts as little-endian bytes, encoding each run of non-blanks once while it is remembered.

    Right for vocabularies whose pieces never span white space and whose added tokens hold none.
    """

    def __init__(self, path: str, memo: int = 300_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        self.model = self.tokenizer.model
        self.letters = str.maketrans(dict(zip(map(chr, range(256)), byte_letters(), strict=True)))
        self.pieces = TwoGenerations(self.piece_ids, memo)
        self.words = TwoGenerations(self.word_ids, memo)

    def piece_ids(self, piece: str) -> bytes:
        found = self.model.tokenize(piece.encode().decode("latin-1").translate(self.letters))
        return pack_ids(f"<{len(found)}I", *[t.id for t in found])

    def word_ids(self, word: str) -> bytes:
        plain = PLAIN.match(word)
        if not plain:
            ids = self.tokenizer.encode(word, add_special_tokens=False).ids
            return pack_ids(f"<{len(ids)}I", *ids)
        letters, marks = plain.groups()
        return self.pieces[letters.lower()] + self.pieces[marks] if marks else self.pieces[letters.lower()]

    def encode(self, texts: list[str], end: bytes) -> Iterator[bytes]:
        for text in texts:
            yield b"".join(map(self.words.__getitem__, RUNS.findall(text))) + end


def best_fit(lengths: list[int], capacity: int) -> list[list[int]]:
    """Best-fit decreasing: each piece, longest first, goes where it leaves the least room."""
    open_by_room: list[list[int]] = [[] for _ in range(capacity + 1)]
    rooms, bins = 0, []  # bit r of rooms: some sequence has room r
    for i in sorted(range(len(lengths)), key=lambda i: -lengths[i]):
        n = lengths[i]
        fits = rooms >> n
        if fits:
            room = n + (fits & -fits).bit_length() - 1
            b = open_by_room[room].pop()
            if not open_by_room[room]:
                rooms &= ~(1 << room)
        else:
            room, b = capacity, len(bins)
            bins.append([])
        bins[b].append(i)
        open_by_room[room - n].append(b)
        rooms |= 1 << (room - n)
    return bins


def fillings(left: list[int], counts: dict[int, int], room: int, waste: int) -> Iterator[tuple[int, ...]]:
    """All undominated sets of lengths that fill `room` with at most `waste` left, least waste first.

    left: distinct lengths, ascending. A set that a single length covers (fits in, and is at least as
    long as all of it) is dominated by that length, so it isn't tried.
    """
    top = bisect_right(left, room)
    if not top:
        if room <= waste:
            yield ()
        return
    single, lengths = left[top - 1], left[top - 1 :: -1] if top == len(left) else left[:top][::-1]
    reach, full, first = [1], (1 << (room + 1)) - 1, None  # bit t of reach[i]: the first i lengths have a set of total t

    def sets(i: int, total: int) -> Iterator[tuple[int, ...]]:
        if not total:
            yield ()
            return
        for at in range(1, i + 1):  # the last length used
            n = lengths[at - 1]
            if reach[at] >> total & 1:
                for c in range(1, min(counts[n], total // n) + 1):
                    if reach[at - 1] >> (total - c * n) & 1:
                        for s in sets(at - 1, total - c * n):
                            yield (*s, *(n,) * c)

    for n in lengths:
        bits, c, step = reach[-1], min(counts[n], room // n), 1
        while c:
            step = min(step, c)
            bits |= bits << (n * step)
            c, step = c - step, 2 * step
        reach.append(bits & full)
        if first is None and reach[-1] >> room & 1:  # no waste: most often the only one that is needed
            first = next(sets(len(reach) - 1, room))
            yield first
    for total in range(room, max(single, room - waste) - 1, -1):
        if reach[-1] >> total & 1:
            for s in [(single,)] if total == single else sets(len(lengths), total):
                if s != first:
                    yield s


def fewest(lengths: list[int], capacity: int) -> int:
    """A number of sequences that no packing is below: by total, and as at most k pieces above capacity / (k + 1) fit in one."""
    n, up = len(lengths), sorted(lengths)
    by_count = (-(-(n - bisect_right(up, capacity // (k + 1))) // k) for k in range(1, 65))
    return max(-(-sum(lengths) // capacity), *by_count)


def better(lengths: list[int], capacity: int, most: int, nodes: int) -> tuple[list[tuple[int, ...]] | None, int]:
    """A packing into at most `most` bins, as lengths, or None, and the nodes that are left."""
    counts: dict[int, int] = {}
    for n in lengths:
        counts[n] = counts.get(n, 0) + 1
    left, pieces = sorted(counts), len(lengths)

    def take(n: int) -> None:
        counts[n] -= 1
        if not counts[n]:
            left.pop(bisect_right(left, n) - 1)

    def give(n: int) -> None:
        counts[n] += 1
        if counts[n] == 1:
            left.insert(bisect_right(left, n), n)

    spare = most * capacity - sum(lengths)  # the waste that such a packing may have
    path: list[tuple[int, ...]] = []
    tried, wastes = [0], [0]  # fillings tried at each depth; they are listed anew after a return, to hold none in memory
    while nodes > 0:
        nodes -= 1
        if not left:
            return path, nodes
        if not tried[-1] and (len(path) % 64 == 0 or pieces <= 256):  # best fit for the rest may do
            rest = [n for n in left for _ in range(counts[n])]
            if len(path) + len(tail := best_fit(rest, capacity)) <= most:
                return [*path, *(tuple(rest[i] for i in b) for b in tail)], nodes
        big = left[-1]
        take(big)
        chosen = next(islice(fillings(left, counts, capacity - big, spare - wastes[-1]), tried[-1], None), None)
        if chosen is None:
            give(big)
            tried.pop()
            wastes.pop()
            if not path:
                return None, nodes
            for n in path[-1]:
                give(n)
            pieces += len(path.pop())
            continue
        tried[-1] += 1
        for n in chosen:
            take(n)
        path.append((big, *chosen))
        pieces -= 1 + len(chosen)
        wastes.append(wastes[-1] + capacity - big - sum(chosen))
        tried.append(0)
    rest = [n for n in left for _ in range(counts[n])]
    tail = best_fit(rest, capacity)
    return ([*path, *(tuple(rest[i] for i in b) for b in tail)] if len(path) + len(tail) <= most else None), 0


def complete(lengths: list[int], capacity: int, nodes: int = 3000) -> list[list[int]]:
    """Pack pieces (all at most `capacity`) into few bins: lists of indexes.

    nodes bounds the search besides one way down, not the pieces: when it is spent the best packing so far is returned.
    """
    best = best_fit(lengths, capacity)
    least = fewest(lengths, capacity) if lengths else 0
    while nodes > 0 and len(best) > least:
        down = len(best)
        found, rest = better(lengths, capacity, len(best) - 1, nodes + down)
        if found is None:
            break
        nodes = min(nodes, rest)
        where: dict[int, list[int]] = {}
        for i, n in enumerate(lengths):
            where.setdefault(n, []).append(i)
        best = [[where[n].pop() for n in b] for b in found]
    return best


def token_pieces(docs: DataFrame, path: str, capacity: int, end_id: int, groups: int, memo: int | None = None) -> DataFrame:
    """Pieces of at most `capacity` tokens: doc_id, piece, start, length, ids_crc32 and the group that packs it.

    Groups are dealt out in turn within each input partition, so that repeated rows don't meet in one. The pieces are
    written before they are dealt, so that a task that is run again over rows in another order loses and doubles none.
    A worker keeps its encoder for its later tasks; given `memo`, each task makes one with a memo of that size instead.
    """

    def cut_up(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        encoder = WordEncoder(path, memo) if memo else once(("word encoder", path), lambda: WordEncoder(path))
        end = np.array([end_id], "<u4").tobytes()
        turn = TaskContext.get().partitionId() * 7919
        for batch in batches:
            texts = [t if isinstance(t, str) else "" for t in batch["text"]]
            rows = []
            for doc_id, ids in zip(batch["doc_id"], encoder.encode(texts, end), strict=True):
                for piece, at in enumerate(range(0, len(ids), 4 * capacity)):
                    own = ids[at : at + 4 * capacity]
                    rows.append((doc_id, piece, at // 4, len(own) // 4, zlib.crc32(own), turn % groups))
                    turn += 1
            out = pd.DataFrame(rows, columns=["doc_id", "piece", "start", "length", "ids_crc32", "group"])
            out["doc_id"] = pd.array([None if x is None else int(x) for x in out["doc_id"]], dtype="Int64")
            yield out

    return cut(docs.selectExpr("cast(doc_id as string) doc_id", "text").mapInPandas(trimmed(cut_up), "doc_id long, piece int, start long, length long, ids_crc32 long, group long"))


def pack(docs: DataFrame, path: str, capacity: int = 4096, end_id: int = 1, group_rows: int = 16_384, memo: int | None = None) -> DataFrame:
    """Pack all documents into few sequences: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    A document is its ids and end_id; longer ones than capacity are cut. Null and empty texts are a
    piece of one token. Repeated rows and null ids are packed like any other row; other columns are
    left out. An empty table gives no rows. memo (see token_pieces) bounds memory and changes no row.
    """
    groups = n_groups(docs.count(), group_rows)

    def fill(pieces: pd.DataFrame) -> pd.DataFrame:
        pieces = pieces.sort_values(["length", "doc_id", "piece"], ascending=False, kind="stable").reset_index(drop=True)
        lengths = pieces["length"].tolist()
        sequence, offset = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64)
        for number, members in enumerate(complete(lengths, capacity)):
            at = 0
            for i in members:
                sequence[i], offset[i] = number, at
                at += lengths[i]
        group = int(pieces["group"].iloc[0])
        return pieces.drop(columns="group").assign(sequence_id=sequence * groups + group, offset=offset)

    schema = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"
    return token_pieces(docs, path, capacity, end_id, groups, memo).groupBy("group").applyInPandas(fill, schema)
