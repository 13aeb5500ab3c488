"""Quotation linking: messages to reply-ordered conversations without their quotes.

Lines are parsed by quote level (``> > text``), attribution lines before a quote go with it, and
quoted passages are cut into normalised sentences, so re-wrapped quotes still match.  A
sentence's original is the earliest message that says it itself, before it in the same conversation or
else anywhere, by preference one of a smaller (conversation, turn); conversations have no dates, so one of a larger
number counts as well, unless that closes a circle of replies.  A message replies to the original of most of the
sentences of its shallowest level that has any (ties: the latest), or, quoting nothing known, to the message before it in its
conversation.  Thread, depth and place follow from the replies by pointer doubling; no thread is gathered in one task.
"""

from __future__ import annotations

import hashlib
import json
import re

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import forget, reach_workers, staged

MARK = re.compile(r"^\s{0,3}(?:>\s?)+")
WROTE = re.compile(r"^\s*(?:on\b.*\bwrote|le\b.*\ba écrit|am\b.*\bschrieb.*|el\b.*\bescribió)\s*:\s*$", re.I)
SENTENCE = re.compile(r"(?<=[.!?])\s+|\n\s*\n")


def quote_level(line: str) -> tuple[int, str]:
    m = MARK.match(line)
    return (m[0].count(">"), line[m.end() :]) if m else (0, line)


def split_levels(text: str | None) -> tuple[str, list[tuple[int, str]]]:
    """The message's own words, and its quoted passages with their levels (from 1)."""
    own: list[str] = []
    passages: list[tuple[int, list[str]]] = []
    last = 0
    for line in (text or "").split("\n"):
        level, rest = quote_level(line)
        if level:
            if last == 0:  # a quote begins: the line that names its author belongs to it
                while own and not own[-1].strip():
                    own.pop()
                if own and WROTE.match(own[-1]):
                    own.pop()
            if level != last:
                passages.append((level, []))
            if not WROTE.match(rest):
                passages[-1][1].append(rest)
        else:
            own.append(line)
        last = level
    return "\n".join(own).strip(), [(level, "\n".join(lines)) for level, lines in passages if any(x.strip() for x in lines)]


def sentences(text: str) -> list[str]:
    """Normalised sentences: case, white space and outer punctuation do not count."""
    out = (re.sub(r"\W+", " ", s).strip().casefold() for s in SENTENCE.split(text))
    return [s for s in out if s]


def fingerprint(sentence: str) -> int:
    return int.from_bytes(hashlib.blake2b(sentence.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "little", signed=True)


def parsed(messages: DataFrame) -> DataFrame:
    """conv_id, turn, role, body, own (hashes of own sentences), quoted (level and hash of quoted sentences)."""
    reach_workers(messages.sparkSession)

    def run(batches):
        for batch in batches:
            bodies, own, quoted = [], [], []
            for text in batch.column(3).to_pylist():
                body, passages = split_levels(text)
                bodies.append(body)
                own.append(sorted({fingerprint(s) for s in sentences(body)}))
                quoted.append([{"level": level, "h": fingerprint(s)} for level, p in passages for s in sentences(p)])
            kind = pa.list_(pa.struct([("level", pa.int32()), ("h", pa.int64())]))
            yield pa.record_batch([*(batch.column(i) for i in range(3)), pa.array(bodies, pa.string()), pa.array(own, pa.list_(pa.int64())), pa.array(quoted, kind)], ["conv_id", "turn", "role", "body", "own", "quoted"])

    cols = [F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.col("role").cast("string").alias("role"), F.col("text").cast("string").alias("text")]
    return messages.select(*cols).mapInArrow(run, "conv_id long, turn long, role string, body string, own array<bigint>, quoted array<struct<level: int, h: bigint>>")


def _chains(nodes: DataFrame, best: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame | None]:
    """Messages with their parents in segments; for each quoting one's segment its thread's head; the messages whose chain has no end."""
    linked = nodes.join(best, ["conv_id", "turn"], "left").select(
        "conv_id", "turn", F.coalesce("qc", F.when(F.col("before").isNotNull(), F.col("conv_id"))).alias("pc"), F.coalesce("qt", "before").alias("pt"), F.col("qc").isNotNull().alias("by_quote")
    )
    # A run of messages that each follow the one before is a segment; only quoting messages begin a further one,
    # so pointers are doubled over those alone, however long conversations are.
    seg = F.sum(F.col("by_quote").cast("long")).over(Window.partitionBy("conv_id").orderBy("turn").rowsBetween(Window.unboundedPreceding, 0))
    linked = linked.withColumn("seg", seg)
    linked = staged(linked.withColumn("step", (F.row_number().over(Window.partitionBy("conv_id", "seg").orderBy("turn")) - 1).cast("long")), "replies")
    homes = linked.select(F.col("conv_id").alias("pc"), F.col("turn").alias("pt"), F.col("seg").alias("up_seg"), F.col("step").alias("up_step"))
    # Of a quoting message: its segment, the segment that it replies into, and its distance from that one's head.
    at = linked.where("by_quote").join(homes, ["pc", "pt"]).select("conv_id", "seg", F.col("pc").alias("ac"), F.col("up_seg").alias("as"), (F.col("up_step") + 1).cast("double").alias("depth"))
    at = staged(at, "pointers")
    # A chain without a circle has at most as many segments as there are quoting messages.
    for _ in range(at.count().bit_length() + 1):
        up = at.select(F.col("conv_id").alias("ac"), F.col("seg").alias("as"), F.col("ac").alias("bc"), F.col("as").alias("bs"), F.col("depth").alias("more"))
        nxt = at.join(up, ["ac", "as"], "left").select("conv_id", "seg", F.coalesce("bc", "ac").alias("ac"), F.coalesce("bs", "as").alias("as"), (F.col("depth") + F.coalesce("more", F.lit(0.0))).alias("depth"), F.col("bc").isNotNull().alias("moved"))
        nxt = staged(nxt, "pointers")
        forget(at)
        at = nxt.drop("moved")
        if nxt.where("moved").isEmpty():
            return linked, at, None
    stuck = linked.where("step = 0 and by_quote").join(nxt.where("moved").select("conv_id", "seg"), ["conv_id", "seg"], "left_semi").select("conv_id", "turn")
    return linked, at, stuck


def _replies(rows: DataFrame) -> DataFrame:
    """conv_id, turn, qc, qt (the message quoted), ahead (it has a larger number)."""
    ids = rows.where("conv_id is not null and turn is not null")
    said = ids.select("conv_id", "turn", F.explode("own").alias("h"))
    here = said.groupBy("conv_id", "h").agg(F.min("turn").alias("t_here"))
    anywhere = said.groupBy("h").agg(F.min(F.struct("conv_id", "turn")).alias("first"))
    asked = ids.select("conv_id", "turn", F.explode("quoted").alias("q")).select("conv_id", "turn", F.col("q.level").alias("level"), F.col("q.h").alias("h"))
    # A very common sentence is one row on the right side of both joins.
    met = asked.join(here, ["conv_id", "h"], "left").join(anywhere, "h", "left")
    there = F.struct(F.col("first.conv_id"), F.col("first.turn"))
    earlier = (F.col("first.conv_id") < F.col("conv_id")) | ((F.col("first.conv_id") == F.col("conv_id")) & (F.col("first.turn") < F.col("turn")))
    found = F.when(F.col("t_here") < F.col("turn"), F.struct("conv_id", F.col("t_here").alias("turn"))).when(earlier | (F.col("first.conv_id") > F.col("conv_id")), there)
    votes = met.select("conv_id", "turn", "level", found.alias("origin")).where("origin is not null").groupBy("conv_id", "turn", "level", "origin").agg(F.count(F.lit(1)).alias("n"))
    back = (F.col("origin.conv_id") <= F.col("conv_id")).cast("int").alias("back")
    best = votes.groupBy("conv_id", "turn").agg(F.max(F.struct((-F.col("level")).alias("level"), back, "n", "origin")).alias("b"))
    return best.select("conv_id", "turn", F.col("b.origin.conv_id").alias("qc"), F.col("b.origin.turn").alias("qt"), (F.col("b.back") == 0).alias("ahead"))


def threads(messages: DataFrame) -> DataFrame:
    """One row for each message: conv_id, turn, role, body, n_quoted, parent_conv, parent_turn, thread_conv, thread_turn, depth, place.

    ``place`` counts from 0 within a thread by conversation and turn.
    Null and empty texts have an empty body; a message with a null conv_id or turn is a thread of its own with a null place.  Rows that repeat
    (conv_id, turn) share their parent.  Very long texts are parsed whole.  Other columns are ignored; an empty table gives no rows.
    """
    rows = staged(parsed(messages), "messages")
    # The message before in the conversation, by a sorted window that streams.
    nodes = rows.where("conv_id is not null and turn is not null").select("conv_id", "turn").distinct()
    nodes = nodes.withColumn("before", F.lag("turn").over(Window.partitionBy("conv_id").orderBy("turn")))
    best = staged(_replies(rows), "quotes")
    for _ in range(2):
        linked, at, stuck = _chains(nodes, best)
        if stuck is None:
            break
        # Links to larger numbers closed circles; without those of the messages in or before one, replies only lead back.
        best = staged(best.where("not ahead").unionByName(best.where("ahead").join(stuck, ["conv_id", "turn"], "left_anti")), "quotes")
    else:
        raise RuntimeError("reply chains did not settle")
    heads = linked.where("step = 0").select(F.col("conv_id").alias("ac"), F.col("seg").alias("as"), F.col("turn").alias("at"))
    quoted = at.join(heads, ["ac", "as"]).select("conv_id", "seg", "ac", "at", F.col("depth").cast("long").alias("depth"))
    plain = linked.where("step = 0 and not by_quote").select("conv_id", "seg", F.col("conv_id").alias("ac"), F.col("turn").alias("at"), F.lit(0).cast("long").alias("depth"))
    at = linked.join(quoted.unionByName(plain), ["conv_id", "seg"]).select("conv_id", "turn", "ac", "at", (F.col("depth") + F.col("step")).alias("depth"))
    order = Window.partitionBy("ac", "at").orderBy("conv_id", "turn")
    placed = at.withColumn("place", F.row_number().over(order) - 1)
    facts = linked.join(placed, ["conv_id", "turn"])
    out = rows.alias("m").join(facts.alias("f"), (F.col("m.conv_id") == F.col("f.conv_id")) & (F.col("m.turn") == F.col("f.turn")), "left")
    return out.select(
        "m.conv_id", "m.turn", "m.role", "m.body", F.size("m.quoted").cast("long").alias("n_quoted"), F.coalesce("f.by_quote", F.lit(False)).alias("by_quote"),
        F.col("f.pc").alias("parent_conv"), F.col("f.pt").alias("parent_turn"), F.coalesce("f.ac", "m.conv_id").alias("thread_conv"), F.coalesce("f.at", "m.turn").alias("thread_turn"), F.coalesce("f.depth", F.lit(0)).cast("long").alias("depth"), F.col("f.place").cast("long").alias("place"),
    )


def conversations(messages: DataFrame, most: int = 1000) -> DataFrame:
    """thread_conv, thread_turn, part, chat: each thread as JSON lists of role and content, in reply order.

    A thread of more than ``most`` messages continues in further parts, so no row grows without bound.
    """
    rows = threads(messages).where("place is not null").select("thread_conv", "thread_turn", F.expr(f"place div {int(most)}").alias("part"), "place", "role", "body")

    def write(batches):
        key, chat = None, []

        def row():
            return pa.record_batch([*(pa.array([k], pa.int64()) for k in key), pa.array([json.dumps(chat, ensure_ascii=False)])], ["thread_conv", "thread_turn", "part", "chat"])

        for batch in batches:
            for c, t, p, _, role, body in zip(*(batch.column(i).to_pylist() for i in range(6))):
                if key is not None and (c, t, p) != key:
                    yield row()
                    chat = []
                key = (c, t, p)
                chat.append({"role": role or "user", "content": body})
        if key is not None:
            yield row()

    by = ["thread_conv", "thread_turn", "part"]
    return rows.repartition(*by).sortWithinPartitions(*by, "place").mapInArrow(write, "thread_conv long, thread_turn long, part long, chat string")
