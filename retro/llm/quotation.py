"""Chat formatting by quotation linking.

A message's lines that begin with `>` marks are quoted; their number is the quote level. Runs of lines of one level are passages, normalised
(marks and surrounding white space away, white space runs to one space, lower case) and hashed. What stands in no quote is the
message's own text; it, its paragraphs, lines, sentences (within a line) and pairs of neighbouring sentences are hashed alike. A passage is linked to the
earliest earlier message of its conversation whose own text, paragraph or line has its hash, or else to the least (conversation, turn) of all others that has it.

A passage that has no such original as a whole is linked by its sentences. Each paragraph, line, sentence and pair names a message by the rule above; of the
named messages that hold more than half of the passage's distinct sentences, one of its own conversation goes first, then the one that holds most
sentences, then most pairs, then the least (conversation, turn).

A message answers the latest message of its conversation that its level-1 passages link to, or else the turn before. Conversations are
ordered by thread (the turn at the root), then depth of reply, then turn, and hold own texts only.

Defined results: null texts are empty; a message of quotes only has an empty content; rows without conv_id or turn are left out; rows that
repeat (conv_id, turn) are one message (the least role and text). Passages without a word link to nothing.
"""

from __future__ import annotations

import re
from hashlib import blake2b

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from retro.llm.runtime import checkpointed

_MARKS = re.compile(r"[ \t]{0,3}((?:>[ \t]?)+)")
_PARAGRAPH, _SENTENCE = re.compile(r"\n[ \t]*\n"), re.compile(r"(?<=[.!?\u3002])\s+")


def normal(text: str) -> str:
    return " ".join(text.split()).lower()


def code_of(text: str) -> int | None:
    """A signed 64-bit hash of the normalised text; None without any."""
    text = normal(text)
    return int.from_bytes(blake2b(text.encode(), digest_size=8).digest(), "little", signed=True) if text else None


def pieces(text: str) -> tuple[list[int], list[int], list[int]]:
    """Distinct hashes of a text's sentences, of pairs of neighbouring sentences, and of its paragraphs and lines."""
    lines = text.split("\n")
    said = [x for line in lines for x in _SENTENCE.split(line.strip()) if normal(x)]
    hashed = lambda texts: sorted({code_of(t) for t in texts} - {None})
    return hashed(said), hashed(map(" ".join, zip(said, said[1:], strict=False))), hashed((*_PARAGRAPH.split(text), *lines))


def parsed(text: str) -> tuple[str, list[tuple[int, int, list[int], list[int], list[int]]], list[int]]:
    """(own text, (level, hash, *pieces) of each quoted passage, hashes of the own text and its paragraphs and lines)."""
    own: list[str] = []
    runs: list[tuple[int, list[str]]] = []
    before = 0
    for line in text.split("\n"):
        m = _MARKS.match(line)
        level = m[1].count(">") if m else 0
        if level:
            if level != before:
                runs.append((level, []))
            runs[-1][1].append(line[m.end() :])
        else:
            own.append(line)
        before = level
    body = "\n".join(own).strip()
    passages = [(level, "\n".join(lines)) for level, lines in runs]
    quotes = [(level, h, *pieces(passage)) for level, passage in passages if (h := code_of(passage)) is not None]
    parts = {code_of(p) for p in (body, *_PARAGRAPH.split(body), *body.split("\n"))} - {None}
    return body, quotes, sorted(parts)


def messages(conversations: DataFrame) -> DataFrame:
    """(conv_id, turn, role, content, quotes, parts, fine) of every message; fine: hashes of sentences and pairs that are no parts."""
    kept = conversations.where("conv_id is not null and turn is not null").select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.col("role").cast("string").alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    one = kept.groupBy("conv_id", "turn").agg(F.min(F.struct("role", "text")).alias("m")).select("conv_id", "turn", "m.role", "m.text")

    def run(batches):
        kind = pa.list_(pa.struct([("level", pa.int32()), ("code", pa.int64()), *((k, pa.list_(pa.int64())) for k in ("sentences", "pairs", "blocks"))]))
        for batch in batches:
            found = [parsed(t) for t in batch.column("text").to_pylist()]
            fine = [sorted({*more[0], *more[1]}.difference(f[2])) for f in found for more in [pieces(f[0])]]
            quotes = pa.array([[dict(zip(("level", "code", "sentences", "pairs", "blocks"), q, strict=True)) for q in f[1]] for f in found], kind)
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in ("conv_id", "turn", "role")), pa.array([f[0] for f in found], pa.string()), quotes, *(pa.array(x, pa.list_(pa.int64())) for x in ([f[2] for f in found], fine))], ["conv_id", "turn", "role", "content", "quotes", "parts", "fine"])

    return one.mapInArrow(run, "conv_id long, turn long, role string, content string, quotes array<struct<level:int,code:long,sentences:array<long>,pairs:array<long>,blocks:array<long>>>, parts array<long>, fine array<long>")


def named(quoted: DataFrame, parsed_messages: DataFrame) -> DataFrame:
    """`quoted` (conv_id, turn, code, ...) with to_conv and to_turn, the message that each hash names; null without an original."""
    asked = quoted.select("code").distinct()
    said = parsed_messages.select("conv_id", "turn", F.explode("parts").alias("code")).join(asked, "code", "left_semi")
    here = said.groupBy("conv_id", "code").agg(F.min("turn").alias("here"))
    # the least message outside a conversation is one of the least two conversations that have the passage
    least = said.groupBy("code").agg(F.min(F.struct("conv_id", "turn")).alias("x"))
    second = said.join(least, "code").where(F.col("conv_id") != F.col("x.conv_id")).groupBy("code").agg(F.min(F.struct("conv_id", "turn")).alias("y"))
    out = quoted.join(here, ["conv_id", "code"], "left").join(least, "code", "left").join(second, "code", "left")
    inside = F.col("here") < F.col("turn")
    other = F.when(F.col("x.conv_id") != F.col("conv_id"), F.col("x")).otherwise(F.col("y"))
    return out.select(*quoted.columns, F.when(inside, F.col("conv_id")).otherwise(other["conv_id"]).alias("to_conv"), F.when(inside, F.col("here")).otherwise(other["turn"]).alias("to_turn"))


def links(parsed_messages: DataFrame) -> DataFrame:
    """(conv_id, turn, place, level, code, to_conv, to_turn) of every quoted passage; to_*: null without an original."""
    key = ["conv_id", "turn", "place"]
    quoted = checkpointed(parsed_messages.select("conv_id", "turn", F.posexplode("quotes").alias("place", "q")).select("conv_id", "turn", "place", "q.*"))
    whole = checkpointed(named(quoted.select(*key, "level", "code"), parsed_messages))
    rest = quoted.join(whole.where("to_conv is null").select(*key), key, "left_semi").select(*key, "sentences", "pairs", "blocks")
    rest = checkpointed(rest)
    if rest.isEmpty():
        return whole
    asked = rest.select(*key, F.explode(F.array_union(F.array_union("sentences", "pairs"), "blocks")).alias("code"))
    every = parsed_messages.select("conv_id", "turn", F.concat("parts", "fine").alias("parts"))
    candidates = named(asked, every).where("to_conv is not null").select(*key, "to_conv", "to_turn").distinct()
    parts = every.select(F.col("conv_id").alias("to_conv"), F.col("turn").alias("to_turn"), "parts")
    held = candidates.join(rest, key).join(parts, ["to_conv", "to_turn"])
    count = lambda c: F.size(F.array_intersect(c, "parts"))
    held = held.withColumn("n", count("sentences")).where(2 * F.col("n") > F.size("sentences"))
    order = F.struct((F.col("to_conv") != F.col("conv_id")).alias("outside"), (-F.col("n")).alias("n"), (-count("pairs")).alias("pairs"), "to_conv", "to_turn")
    best = held.groupBy(*key).agg(F.min(order).alias("best"))
    out = whole.join(best, key, "left")
    return out.select(*key, "level", "code", F.coalesce("to_conv", "best.to_conv").alias("to_conv"), F.coalesce("to_turn", "best.to_turn").alias("to_turn"))


def reply_ordered(conversations: DataFrame) -> DataFrame:
    """(conv_id, turn, role, reply_to, depth, thread, position, n_quotes, n_linked, content) of every message, content without quotes."""
    parts = checkpointed(messages(conversations))
    found = links(parts)
    own = (F.col("level") == 1) & (F.col("to_conv") == F.col("conv_id"))
    tally = found.groupBy("conv_id", "turn").agg(F.count("*").alias("n_quotes"), F.count("to_conv").alias("n_linked"), F.max(F.when(own, F.col("to_turn"))).alias("answers"))
    before = F.lag("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    tree = parts.select("conv_id", "turn", before.alias("before")).join(tally, ["conv_id", "turn"], "left")
    tree = tree.select("conv_id", "turn", F.coalesce("answers", "before").alias("reply_to"), F.coalesce("n_quotes", F.lit(0)).alias("n_quotes"), F.coalesce("n_linked", F.lit(0)).alias("n_linked"))
    # pointer doubling: after k rounds `up` is the ancestor 2^k steps away. Messages that reached their root leave the rounds.
    tree = checkpointed(tree.withColumn("up", F.col("reply_to")).withColumn("thread", F.coalesce("reply_to", "turn")).withColumn("depth", F.when(F.col("reply_to").isNull(), 0).otherwise(1).cast("long")))
    columns = tree.columns
    done, moving = tree.where("up is null"), tree.where("up is not null")
    while not moving.isEmpty():
        ups = moving.select("conv_id", "up").distinct()
        known = done.unionByName(moving).select("conv_id", F.col("turn").alias("up"), F.col("up").alias("up2"), F.col("thread").alias("thread2"), F.col("depth").alias("depth2"))
        jump = known.join(ups, ["conv_id", "up"], "left_semi")
        moved = moving.join(jump, ["conv_id", "up"]).select("conv_id", "turn", "reply_to", "n_quotes", "n_linked", F.col("up2").alias("up"), F.col("thread2").alias("thread"), (F.col("depth") + F.col("depth2")).alias("depth"))
        moved = checkpointed(moved)
        done = done.unionByName(moved.where("up is null").select(*columns))
        moving = moved.where("up is not null")
    tree = done
    out = tree.join(parts.select("conv_id", "turn", "role", "content"), ["conv_id", "turn"])
    position = F.row_number().over(Window.partitionBy("conv_id").orderBy("thread", "depth", "turn"))
    return out.select("conv_id", "turn", "role", "reply_to", "depth", "thread", position.cast("long").alias("position"), "n_quotes", "n_linked", "content")


def chats(conversations: DataFrame) -> DataFrame:
    """(conv_id, n_messages, messages) of every conversation: its own texts in reply order."""
    line = F.struct("position", "role", "content")
    held = reply_ordered(conversations).groupBy("conv_id").agg(F.count("*").alias("n_messages"), F.sort_array(F.collect_list(line)).alias("messages"))
    return held.select("conv_id", "n_messages", F.transform("messages", lambda m: F.struct(m["role"].alias("role"), m["content"].alias("content"))).alias("messages"))
