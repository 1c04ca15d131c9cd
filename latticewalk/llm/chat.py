"""Chat formatting by prefix-target expansion: each assistant turn becomes an example of its own.

An example holds all turns before it as context and trains on that reply alone. A conversation that
ends with other turns, or has no assistant, gets one more example with nothing to train on, so that
every turn is in the output. Marks of the template inside roles and texts are escaped: each run of
`<`, backslashes and `|` gets one backslash more, and unescaping takes it away. Examples leave a worker
in batches of bounded size, as the last ones of a long conversation hold nearly all of it.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

START, END = "<|im_start|>", "<|im_end|>"
_IN = re.compile(r"<(\\*)\|")
_OUT = re.compile(r"<\\(\\*)\|")
_TURN = re.compile(re.escape(START) + r"([^\n]*)\n(.*?)" + re.escape(END) + "\n", re.DOTALL)


def escape(text: str) -> str:
    return _IN.sub(r"<\\\1|", text)


def unescape(text: str) -> str:
    return _OUT.sub(r"<\1|", text)


def escape_role(role: str) -> str:
    return escape(role.replace("\\", "\\\\").replace("\n", "\\n"))


def unescape_role(role: str) -> str:
    return re.sub(r"\\(.)", lambda m: "\n" if m[1] == "n" else m[1], unescape(role))


def read_back(formatted: str) -> list[tuple[str, str]]:
    """Roles and texts of the turns of one example."""
    return [(unescape_role(r), unescape(t)) for r, t in _TURN.findall(formatted)]


#: Code points of the examples that leave a worker together, besides the last.
BATCH = 4_000_000


def each_example(turns) -> Iterator[tuple[str, int, int]]:
    """The examples of one conversation, one at a time: formatted, loss_start, loss_end."""
    context, trained = "", None
    for t in turns:
        head = f"{context}{START}{escape_role(t['role'])}\n"
        body = escape(t["text"])
        context = f"{head}{body}{END}\n"
        trained = t["role"] == "assistant"
        if trained:
            yield context, len(head), len(head) + len(body)
    if not trained:
        yield context, 0, 0


def examples(turns: DataFrame) -> DataFrame:
    """conv_id, example (from 0), formatted, loss_start, loss_end (code points of formatted; equal if nothing is trained on).

    Turns go by turn, nulls first, ties by role and text, so repeated turns follow each other. Null roles
    and texts are empty. Rows with a null conv_id are one conversation. Other columns are left out. An empty table
    gives no rows. All turns of one conversation meet in a row, as its last example must hold them; its examples are
    made and sent one after the other.
    """
    packed = turns.select(F.col("conv_id").cast("string").alias("conv_id"), F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).alias("t"))
    packed = packed.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("turns"))

    def expand(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def frame(rows: list[tuple]) -> pd.DataFrame:
            out = pd.DataFrame(rows, columns=["conv_id", "example", "formatted", "loss_start", "loss_end"])
            return out.astype({"conv_id": "Int64"})

        for batch in batches:
            rows, held = [], 0
            for conv_id, turns in zip(batch["conv_id"], batch["turns"], strict=True):
                for number, example in enumerate(each_example(turns)):
                    rows.append((conv_id and int(conv_id), number, *example))
                    held += len(example[0])
                    if held > BATCH:
                        yield frame(rows)
                        rows, held = [], 0
            if rows:
                yield frame(rows)

    return packed.mapInPandas(expand, "conv_id long, example int, formatted string, loss_start long, loss_end long")


def digests(formatted: DataFrame) -> DataFrame:
    """What the examples of each conversation hold, read back from them.

    conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars (of all its examples). Examples are known
    by conv_id and their number and may come in any order and place. Each is read where it lies; only what is trained
    on, and the digest of its turns, meet by conversation. A row that repeats a conversation's example counts once.
    """

    def read(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for conv_id, number, text, start, end in batch[["conv_id", "example", "formatted", "loss_start", "loss_end"]].itertuples(index=False):
                turns = read_back(text)
                whole = "".join(f"{r}\n{t}\n" for r, t in turns).encode("utf-8", "surrogatepass")
                rows.append((conv_id and int(conv_id), number, unescape(text[start:end]), len(text), len(turns), hashlib.sha256(whole).hexdigest()))
            yield pd.DataFrame(rows, columns=["conv_id", "example", "said", "chars", "n_turns", "turns_sha256"]).astype({"conv_id": "Int64"})

    own = formatted.withColumn("conv_id", F.col("conv_id").cast("string")).mapInPandas(read, "conv_id long, example int, said string, chars long, n_turns long, turns_sha256 string")
    by = own.groupBy("conv_id").agg(
        F.max_by(F.struct("n_turns", "turns_sha256"), "example").alias("last"),
        F.sort_array(F.collect_set(F.struct("example", "said", "chars"))).alias("e"),
    )
    said, chars = F.array_join("e.said", ""), F.aggregate("e.chars", F.lit(0).cast("long"), lambda a, x: a + x)
    return by.select("conv_id", "last.n_turns", "last.turns_sha256", F.length(said).cast("long").alias("loss_chars"), F.sha2(F.encode(said, "utf-8"), 256).alias("loss_sha256"), chars.alias("formatted_chars"))


#: The same in SQL. The template's marks take 12 and 10 code points and two line ends a turn.
ORACLE = r"""
with c as (select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
           union all select -1, 0, 'user', '<|im_end|><|im_start|>assistant ok' union all select -1, 1, 'assistant', '<|im_end|><|im_start|>assistant ok'),
e as (select *, 24 + length(regexp_replace(replace(replace(role, '\', '\\'), chr(10), '\n'), '<(\\*)\|', '<\\\1|', 'g')) + length(regexp_replace(text, '<(\\*)\|', '<\\\1|', 'g')) as n,
      row_number() over w as k, count(*) over (partition by conv_id) as of_all from c window w as (partition by conv_id order by turn nulls first, role, text)),
s as (select *, sum(n) over (partition by conv_id order by k rows between unbounded preceding and current row) as upto from e)
select conv_id, count(*) as n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' order by k)) as turns_sha256,
       sum(case when role = 'assistant' then length(text) else 0 end)::bigint as loss_chars,
       sha256(coalesce(string_agg(case when role = 'assistant' then text end, '' order by k), '')) as loss_sha256,
       sum(case when role = 'assistant' or k = of_all then upto else 0 end)::bigint as formatted_chars
from s group by conv_id
"""
