"""Exact token counts at every prefix of a text, by dynamic programming over byte prefixes.

A byte-pair encoding is valid exactly if every two neighbouring tokens stay two tokens when
they are encoded together. So the last token of the encoding of each prefix follows from the
last tokens of the shorter prefixes, and the count is one more than theirs. Counts for all
prefixes of a text are stored as one signed byte per character, the change of the count;
truncation and budget questions are answered from it and nothing is encoded again.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterator
from itertools import accumulate

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from latticewalk.llm.common import once

#: White space and the pieces into which byte-level BPE first splits a text: fixed values of the public vocabulary's format.
SPACE = r"\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
PIECES = regex.compile(rf"'(?:s|t|re|ve|m|ll|d)| ?\p{{L}}+| ?\p{{N}}+| ?[^{SPACE}\p{{L}}\p{{N}}]+|[{SPACE}]+(?![^{SPACE}])|[{SPACE}]+")
#: A run of blanks with the text up to the next: no piece spans from such a unit into the next one.
UNITS = re.compile(r"[ \n]*[^ \n]+|[ \n]+")
ODD_SPACE = re.compile(r"[\t\v\f\r\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]")
ODD_UNITS = regex.compile(rf"[{SPACE}]*[^{SPACE}]+|[{SPACE}]+")
#: A unit whose pieces can be counted one by one at every prefix.
SIMPLE = re.compile(r"[ \n]?[^ \n']+\Z")


def byte_letters() -> list[str]:
    """The letter by which a byte-level vocabulary writes each byte: printable ones stand for themselves, others follow from 256 on."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(rest)) for b in range(256)]


class TwoGenerations(dict):
    """A memo of bounded size: entries not asked for since the last turn are forgotten."""

    def __init__(self, make, size: int):
        super().__init__()
        self.make, self.size, self.old = make, size, {}

    def __missing__(self, key):
        found = self.old.get(key)
        if found is None:
            found = self.make(key)
        if len(key) <= 64:
            if len(self) >= self.size:
                self.old = dict(self)
                self.clear()
            self[key] = found
        return found


class PrefixCounter:
    """Token counts of all prefixes of texts under a byte-level BPE vocabulary in the JSON format of the tokenizers library."""

    def __init__(self, path: str, memo: int = 300_000):
        with open(path, encoding="utf-8") as f:
            j = json.load(f)
        model = j["model"]
        merges = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        self.rank = {pair: i for i, pair in enumerate(merges)}
        self.vocab = {t for t in model["vocab"] if len(self.merged(t)) == 1}
        self.longest = max(map(len, self.vocab))
        self.letters = dict(zip(map(chr, range(256)), byte_letters(), strict=True))
        self.table = str.maketrans(self.letters)
        special = sorted((t["content"] for t in j["added_tokens"]), key=len, reverse=True)
        self.specials = re.compile("|".join(map(re.escape, special))) if special else None
        self.pairs: dict[str, dict[str, bool]] = {}
        self.n_pairs = 0
        self.heads: dict[str, tuple[list[str], list[int]]] = {}
        self.pieces = TwoGenerations(self.piece_counts, 20_000)
        self.simple = TwoGenerations(self.piece_changes, memo)
        self.units = TwoGenerations(self.unit_changes, memo)

    def merged(self, text: str) -> list[str]:
        """The encoding of a short piece by applying merges in order of rank."""
        parts = list(text)
        while len(parts) > 1:
            rank, at = min((self.rank.get((a, b), 1 << 60), i) for i, (a, b) in enumerate(zip(parts, parts[1:])))
            if rank == 1 << 60:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    def stays(self, left: str, right: str) -> bool:
        """Whether two tokens stay apart when encoded together."""
        if self.n_pairs > 1_000_000:
            self.pairs.clear()
            self.n_pairs = 0
        ok = self.merged(left + right) == [left, right]
        self.pairs.setdefault(left, {})[right] = ok
        self.n_pairs += 1
        return ok

    def piece_counts(self, piece: str) -> list[int]:
        """Counts at each byte prefix of one piece (in the vocabulary's letters), the empty one first."""
        vocab, longest, pairs, none = self.vocab, self.longest, self.pairs, {}
        head = piece[:6]  # many pieces begin alike
        known = self.heads.get(head)
        last, counts = known and ([*known[0]], [*known[1]]) or ([""], [0])
        for i in range(len(counts), len(piece) + 1):
            for j in range(i - longest if i > longest else 0, i):
                token = piece[j:i]
                if token in vocab:
                    if j:
                        left = last[j]
                        ok = pairs.get(left, none).get(token)
                        if ok is None:
                            ok = self.stays(left, token)
                        if not ok:
                            continue
                    last.append(token)
                    counts.append(counts[j] + 1)
                    break
            else:
                raise ValueError(f"no encoding ends at {i} of {piece!r}")
        if not known and len(piece) >= 6:
            if len(self.heads) >= 100_000:
                self.heads.clear()
            self.heads[head] = last[:7], counts[:7]
        return counts

    def letters_of(self, text: str) -> str:
        return text.encode("utf-8", "surrogatepass").decode("latin-1").translate(self.table)

    def plain_counts(self, text: str) -> np.ndarray:
        """Counts at each character prefix of a text that ends with its last piece as if the text ended there."""
        out, done = [0], 0
        spans = [m.span() for m in PIECES.finditer(text)]
        for k, (start, end) in enumerate(spans):
            piece = text[start:end]
            counts = self.pieces[self.letters_of(piece)]
            if piece.isascii():
                inner = counts[1:]
            else:
                at, inner = 0, []
                for ch in piece:
                    at += len(ch.encode("utf-8", "surrogatepass"))
                    inner.append(counts[at])
            out += [done + c for c in inner]
            done += counts[-1]
            if k and text[start - 1].isspace():  # a text cut inside a run of blanks has the run so far as one piece
                run, upto = spans[k - 1][0], end if piece.isspace() else start + (piece[0] == " ")
                if text[run:upto].isspace() and upto > start:
                    whole, at = self.pieces[self.letters_of(text[run:upto])], len(text[run:start].encode())
                    for i in range(start, upto):
                        at += len(text[i].encode())
                        out[i + 1] = out[run] + whole[at]
        return np.array(out, dtype=np.int64)

    def unit_counts(self, unit: str) -> np.ndarray:
        out = self.plain_counts(unit)
        if "'" in unit:  # a contraction that is cut is two pieces
            for m in regex.finditer(r"'(?:re|ve|ll)", unit):
                if any(s == m.span() for s in (x.span() for x in PIECES.finditer(unit))):
                    out[m.start() + 2] = sum(self.pieces[self.letters_of(p)][-1] for p in PIECES.findall(unit[: m.start() + 2]))
        return out

    def piece_changes(self, piece: str) -> bytes:
        counts = self.piece_counts(self.letters_of(piece))
        if not piece.isascii():
            ends = accumulate(1 if c < "\x80" else 2 if c < "\u0800" else 3 if c < "\U00010000" else 4 for c in piece)
            counts = [0, *[counts[at] for at in ends]]
        return bytes([(b - a) & 255 for a, b in zip(counts, counts[1:])])

    def unit_changes(self, unit: str) -> bytes:
        if SIMPLE.match(unit) and not ODD_SPACE.search(unit):
            return b"".join(map(self.simple.__getitem__, PIECES.findall(unit)))
        return np.diff(self.unit_counts(unit)).astype(np.int8).tobytes()

    def changes(self, text: str) -> bytes:
        """The change of the count at each character of the text, one signed byte each."""
        out, at = [], 0
        for m in self.specials.finditer(text) if self.specials else ():
            # up to its last character a special string is plain text; with that the whole of it is one token
            change = self.plain_changes(text[at : m.end() - 1])
            counts = np.frombuffer(change, np.int8)
            last = 1 - int(counts[m.start() - at :].sum(dtype=np.int64))
            out += [change, np.int8(last).tobytes()]
            at = m.end()
        return b"".join([*out, self.plain_changes(text[at:])])

    def plain_changes(self, text: str) -> bytes:
        """The same of a text in which no special string counts as one."""
        units = (ODD_UNITS if ODD_SPACE.search(text) else UNITS).findall(text)
        return b"".join(map(self.units.__getitem__, units))

    def total(self, text: str) -> int:
        return int(np.frombuffer(self.changes(text), np.int8).sum(dtype=np.int64))


def prefix_counts(changes: bytes) -> np.ndarray:
    """The exact token count of every prefix, the empty one first."""
    return np.concatenate([[0], np.frombuffer(changes, np.int8).cumsum(dtype=np.int64)])


def longest_prefix(changes: bytes, budget: int) -> int:
    """Characters of the longest prefix with at most `budget` tokens; counts may fall when a character completes a token."""
    return int(np.flatnonzero(prefix_counts(changes) <= budget)[-1]) if budget >= 0 else 0


def count_tokens(docs: DataFrame, path: str, limit: int = 1024, store: bool = False) -> DataFrame:
    """Token counts of every whole text: doc_id, n_bytes, n_tokens, over_limit and, with store, the prefix table `changes`.

    A null text counts as empty (no bytes, no tokens). Repeated rows and null ids give a row each;
    other columns are left out, so their names can't clash. Empty tables give no rows.
    """
    schema = "n_bytes long, n_tokens long" + ", changes binary" * store

    @F.pandas_udf(schema)
    def count(parts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        counter = once(("prefix counts", path), lambda: PrefixCounter(path))
        for part in parts:
            rows = []
            for text in part:
                text = text if isinstance(text, str) else ""
                changes = counter.changes(text)
                n = int(np.frombuffer(changes, np.int8).sum(dtype=np.int64))  # the count at the last prefix
                rows.append((len(text.encode("utf-8", "surrogatepass")), n, changes)[: 2 + store])
            yield pd.DataFrame(rows, columns=["n_bytes", "n_tokens", "changes"][: 2 + store])

    out = docs.select("doc_id", count("text").alias("c")).select("doc_id", "c.*")
    return out.withColumn("over_limit", F.col("n_tokens") > limit)
