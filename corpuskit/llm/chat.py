"""Reply-ordered conversations by linking quotations to their originals (operator 6).

A message is parsed into its own text and quoted passages with their nesting levels. The
normalised passages, and their single lines, are hashed, and so are the whole text, the
paragraphs and the lines that each message says itself. The earliest message of the same
conversation that says a hash is its original: one row for each (conversation, hash), so
the join stays linear even if one line is in every message. The original of a message's
outermost linked passage is what it replies to (the latest one, if it quotes several).
Following replies upwards, by pointer jumping, gives each message the head of its thread;
ordering by (conversation, thread, turn) puts every reply behind what it answers, and a
conversation without quotations stays in the order of its turns.

Defined cases: a null text is an empty message; a message that only quotes has an empty
text; a quotation without an earlier original is dropped from the text but not linked;
repeated rows stay, with equal results; null conversation or turn values are kept and
linked to nothing; only the four named columns are read; an empty table gives an empty
result.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from hashlib import blake2b

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpuskit.llm.common import small, stored

_QUOTE = re.compile(r"^\s{0,3}((?:>\s?)+)(.*)$", re.S)
_INTRO = re.compile(r"^.{0,200}\b(?:wrote|writes|schrieb|a écrit|escribió)\s*:\s*$", re.I)


def normalised(text: str) -> str:
    return " ".join(text.casefold().split())


def passage_hash(text: str) -> int | None:
    """Hash of the normalised passage; None if nothing is left of it."""
    clean = normalised(text)
    return int.from_bytes(blake2b(clean.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "little", signed=True) if clean else None


def parse(text: str | None) -> tuple[str, list[tuple[int, str]]]:
    """Own text without quotations and their introductions, and the passages as (level, text)."""
    own: list[str] = []
    passages: list[tuple[int, list[str]]] = []
    level_now = 0
    for line in (text or "").split("\n"):
        m = _QUOTE.match(line)
        level = m[1].count(">") if m else 0
        if level:
            if level != level_now:
                passages.append((level, []))
                if not level_now and own and _INTRO.match(own[-1]):
                    own.pop()
            passages[-1][1].append(m[2])
        else:
            own.append(line)
        level_now = level
    body = re.sub(r"\n{3,}", "\n\n", "\n".join(own)).strip()
    return body, [(level, "\n".join(lines)) for level, lines in passages if "".join(lines).strip()]


def _parse_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in small(batches):
        bodies, said, quoted = [], [], []
        for text in batch.column(3).to_pylist():
            body, passages = parse(text)
            bodies.append(body)
            units = {body, *re.split(r"\n\s*\n", body), *body.split("\n")}
            said.append(sorted({h for u in units if (h := passage_hash(u)) is not None}))
            found = []
            for n, (level, passage) in enumerate(passages):
                for exact, unit in ((0, passage), *((1, line) for line in passage.split("\n"))):
                    h = passage_hash(unit)
                    if h is not None:
                        found.append({"passage": n, "level": level, "exact": exact, "hash": h})
            quoted.append(found)
        kind = pa.list_(pa.struct([("passage", pa.int32()), ("level", pa.int32()), ("exact", pa.int32()), ("hash", pa.int64())]))
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), batch.column(1), batch.column(2), pa.array(bodies, pa.string()), pa.array(said, pa.list_(pa.int64())), pa.array(quoted, kind)],
            ["conv_id", "turn", "role", "content", "said", "quoted"],
        )


def parsed_messages(df: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    rows = df.select(
        F.col(conv_col).cast("long").alias("conv_id"), F.col(turn_col).cast("long").alias("turn"),
        F.col(role_col).cast("string").alias("role"), F.col(text_col).cast("string").alias("text"),
    )
    kind = "array<struct<passage: int, level: int, exact: int, hash: bigint>>"
    return rows.mapInArrow(_parse_rows, f"conv_id long, turn long, role string, content string, said array<long>, quoted {kind}")


def link_quotations(messages: DataFrame) -> DataFrame:
    """``conv_id, turn, parent_turn, n_linked`` for the turns that quote an earlier message; from :func:`parsed_messages`."""
    asked = stored(
        messages.filter("size(quoted) > 0 and conv_id is not null and turn is not null")
        .select("conv_id", "turn", F.explode("quoted").alias("q")).select("conv_id", "turn", "q.*").distinct(),
        "quoted",
    )
    # only hashes that someone quotes need an original: the small side prunes before the grouping
    wanted = asked.select("conv_id", "hash").distinct()
    said = messages.filter("conv_id is not null and turn is not null").select("conv_id", "turn", F.explode("said").alias("hash"))
    first = stored(said.groupBy("conv_id", "hash").agg(F.min("turn").alias("source")).join(wanted, ["conv_id", "hash"], "left_semi"), "originals")
    met = asked.join(first, ["conv_id", "hash"]).filter("source < turn")
    passages = met.groupBy("conv_id", "turn", "passage", "level").agg(F.min(F.struct("exact", F.negate("source").alias("back"))).alias("best"))
    return passages.groupBy("conv_id", "turn").agg(
        F.min(F.struct("level", F.col("best.back").alias("back"))).alias("m"), F.count("*").alias("n_linked")
    ).select("conv_id", "turn", F.negate("m.back").alias("parent_turn"), "n_linked")


def thread_heads(links: DataFrame) -> DataFrame:
    """``conv_id, turn, parent_turn, n_linked, thread_turn, depth``: each step doubles the way followed."""
    state = stored(links.withColumns({"thread_turn": F.col("parent_turn"), "depth": F.lit(1).cast("long")}), "threads")
    while True:
        up = state.select("conv_id", F.col("turn").alias("thread_turn"), F.col("thread_turn").alias("above"), F.col("depth").alias("more"))
        step = stored(
            state.join(up, ["conv_id", "thread_turn"], "left").select(
                "conv_id", "turn", "parent_turn", "n_linked", F.coalesce("above", "thread_turn").alias("thread_turn"),
                (F.col("depth") + F.coalesce("more", F.lit(0))).alias("depth"), F.col("above").isNotNull().alias("moved"),
            ),
            "threads",
        )
        state = step.drop("moved")
        if step.filter("moved").isEmpty():
            return state


def format_conversations(df: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """One row for each message, to be read in the order (conv_id, thread_turn, turn).

    ``content`` has no quotations; ``formatted`` is the message in chat markup.
    """
    messages = stored(parsed_messages(df, conv_col, turn_col, role_col, text_col), "messages")
    links = stored(link_quotations(messages), "links")
    heads = thread_heads(links)
    row = messages.select("conv_id", "turn", "role", "content", F.size("quoted").alias("n"), F.coalesce(F.array_max(F.transform("quoted", lambda q: q["passage"])) + 1, F.lit(0)).alias("n_quotes"))
    out = row.join(heads, ["conv_id", "turn"], "left")
    markup = F.concat(F.lit("<|"), F.coalesce("role", F.lit("unknown")), F.lit("|>\n"), F.col("content"), F.lit("\n"))
    return out.select(
        "conv_id", F.coalesce("thread_turn", "turn").alias("thread_turn"), "turn", "role", "content", "parent_turn",
        F.coalesce("depth", F.lit(0)).cast("long").alias("depth"), F.col("n_quotes").cast("long").alias("n_quotes"),
        F.coalesce("n_linked", F.lit(0)).cast("long").alias("n_linked"), markup.alias("formatted"),
    )
