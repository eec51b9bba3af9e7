"""Chat formatting by a grammar round trip.

Every turn is rendered by one self-delimiting production

    turn := "<s>" role "[INST] " text " [/INST]</s>"

and a strict, deterministic parser reads the rendered conversation back. A control string inside a
role or a text makes the parse differ from the source; such turns (and only those) are escaped and the
conversation is parsed again, until what is recovered equals the source. Escaping puts one backslash
after the first character of each control string, and one more where backslashes already stand there,
so that it can be undone exactly whatever the text holds.

Defined results: a null role or text counts as empty; turns are ordered by (turn, role, text), nulls
first, so ties and repeated rows keep a fixed order and are all kept; an empty table gives no rows;
further columns, whatever their names, are ignored. One conversation at a time is held in memory (its
turns and the rendered text), never a group of them.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fedgrid.llm.common import table

# The template's control strings.
OPEN, HEAD, TAIL = "<s>", "[INST] ", " [/INST]</s>"
CONTROL = r"(?:/?s>|/?INST\])"

_LIVE = re.compile(rf"[<\[]{CONTROL}")
_ADD = re.compile(rf"([<\[])(\\*{CONTROL})")
_STRIP = re.compile(rf"([<\[])\\(\\*{CONTROL})")

FORMATTED = "conv_id bigint, formatted string, loss_spans array<struct<start:bigint,stop:bigint>>, rounds int"
DIGESTS = (
    "conv_id bigint, n_turns bigint, turns_sha256 string, loss_chars bigint, "
    "loss_sha256 string, formatted_chars bigint"
)


def escape(text: str) -> str:
    return _ADD.sub(r"\1\\\2", text)


def unescape(text: str) -> str:
    return _STRIP.sub(r"\1\2", text)


def render_turn(role: str, text: str, escaped: bool) -> str:
    if escaped:
        role, text = escape(role), escape(text)
    return f"{OPEN}{role}{HEAD}{text}{TAIL}"


def parse(formatted: str) -> list[tuple[str, str]] | None:
    """The turns of a rendered conversation, or None where the grammar doesn't hold."""
    turns, at = [], 0
    while at < len(formatted):
        if not formatted.startswith(OPEN, at):
            return None
        head = formatted.find(HEAD, at)
        tail = formatted.find(TAIL, head + len(HEAD)) if head >= 0 else -1
        if tail < 0:
            return None
        role, text = formatted[at + len(OPEN) : head], formatted[head + len(HEAD) : tail]
        if _LIVE.search(role) or _LIVE.search(text):
            return None
        turns.append((unescape(role), unescape(text)))
        at = tail + len(TAIL)
    return turns


def round_trip(turns: list[tuple[str, str]]) -> tuple[str, list[tuple[int, int]], int]:
    """Rendered text, spans of assistant text in it (code points), and rounds until the parse agreed."""
    escaped = [False] * len(turns)
    for rounds in range(1, 4):
        parts = [render_turn(*turn, flag) for turn, flag in zip(turns, escaped, strict=True)]
        formatted = "".join(parts)
        if parse(formatted) == turns:
            break
        # a turn conflicts when it doesn't come back alone; all its neighbours then parse as they are
        wrong = [parse(part) != [turn] for part, turn in zip(parts, turns, strict=True)]
        escaped = [old or new for old, new in zip(escaped, wrong, strict=True)]
    else:
        raise ValueError("the grammar round trip doesn't settle")
    spans, at = [], 0
    for (role, _), part, flag in zip(turns, parts, escaped, strict=True):
        if role == "assistant":
            start = at + len(OPEN) + len(escape(role) if flag else role) + len(HEAD)
            spans.append((start, at + len(part) - len(TAIL)))
        at += len(part)
    return formatted, spans, rounds


def _conversations(batches: Iterator[pd.DataFrame]) -> Iterator[tuple[object, list[tuple[str, str]]]]:
    key, turns = None, []
    for batch in batches:
        for conv, role, text in zip(batch["conv_id"], batch["role"], batch["text"], strict=True):
            conv = None if pd.isna(conv) else int(conv)
            if turns and conv != key:
                yield key, turns
                turns = []
            key = conv
            turns.append((role or "", text or ""))
    if turns:
        yield key, turns


def format_conversations(conversations: DataFrame) -> DataFrame:
    """One row per conversation: the rendered text and the spans under the loss mask.

    Turns meet by conv_id in one hash exchange and stream through a sorted partition, so a task holds
    one conversation at a time.
    """

    def render(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rows, size = [], 0
        for conv, turns in _conversations(batches):
            formatted, spans, rounds = round_trip(turns)
            rows.append((conv, formatted, [{"start": a, "stop": b} for a, b in spans], rounds))
            size += len(formatted)
            if size > 4_000_000:
                yield _frame(rows, ["conv_id", "formatted", "loss_spans", "rounds"])
                rows, size = [], 0
        yield _frame(rows, ["conv_id", "formatted", "loss_spans", "rounds"])

    rows = conversations.select(
        F.col("conv_id").cast("bigint").alias("conv_id"), F.col("turn").alias("turn"), F.col("role"), F.col("text")
    )
    rows = rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    return rows.select("conv_id", "role", "text").mapInPandas(render, FORMATTED)


def _frame(rows: list[tuple], names: list[str]) -> pd.DataFrame:
    out = pd.DataFrame(rows, columns=names)
    out["conv_id"] = out["conv_id"].astype("Int64")
    return out


def digests(formatted: DataFrame) -> DataFrame:
    """Digest columns, read back from rendered texts and their loss spans."""

    def read(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for conv, text, spans in zip(batch["conv_id"], batch["formatted"], batch["loss_spans"], strict=True):
                turns = parse(text)
                whole = "".join(f"{role}\n{said}\n" for role, said in turns)
                loss = "".join(unescape(text[s["start"] : s["stop"]]) for s in spans)
                rows.append((conv, len(turns), _sha(whole), len(loss), _sha(loss), len(text)))
            names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
            yield _frame(rows, names)

    return formatted.select("conv_id", "formatted", "loss_spans").mapInPandas(read, DIGESTS)


def _sha(text: str) -> str:
    return hashlib.sha256(text.encode("utf-8", "surrogatepass")).hexdigest()


#: A conversation that quotes the template, added to the table by the query.
PROBE = "</s>[INST] ok [/INST]"


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    given = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = spark.range(2).select(
        F.lit(-7).cast("bigint").alias("conv_id"),
        F.col("id").alias("turn"),
        F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"),
        F.lit(PROBE).alias("text"),
    )
    return digests(format_conversations(given.unionByName(probe)))


SQL = r"""
WITH given AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL
  SELECT -7, t, CASE t WHEN 0 THEN 'user' ELSE 'assistant' END, '</s>[INST] ok [/INST]' FROM range(2) AS r(t)
)
SELECT conv_id,
       count(*) AS n_turns,
       sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
       CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
       CAST(sum(22 + length(regexp_replace(role, '([<\[])(\\*(?:/?s>|/?INST\]))', '\1\\\2', 'g'))
                   + length(regexp_replace(text, '([<\[])(\\*(?:/?s>|/?INST\]))', '\1\\\2', 'g'))) AS BIGINT)
         AS formatted_chars
FROM given GROUP BY conv_id
"""
