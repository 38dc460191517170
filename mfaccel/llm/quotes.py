"""Quotation linking: replies are joined to the messages that they quote, and lose the quotes.

DataFrame functions only. A line's quote level is the number of leading ">" marks. Runs of lines of one level
are passages; a passage, each of its paragraphs (parts between blank lines) and each of its lines give keys: a hash of the
text in lower case with single spaces. A message is known by the keys of its own text (level 0), its paragraphs
and its lines. A key links to the first message that has it: in the same conversation before the quoting one, else
in any other conversation. The longest unit that is found decides; of equal ones the lowest level, then the one that
stands first.

Only messages with a quote give quote keys, and only keys that are quoted are looked up, the first messages of two conversations a key, so a
text that a third of all messages share is one row on that side of the join. Roots and depths are found by doubling
the steps to the parent, a logarithmic number of joins; chains across conversations count too, and a message that is
quoted in a ring keeps the least message of the ring as its root. Threads come out in reply order.

Edge cases: a null text is empty and neither quotes nor is quoted; blank units give no key; repeated rows (same
conversation and turn) are one message, the least text; messages whose conversation or turn is null stand alone, with no reply, and
repeat as they are; an unknown quote is removed from the text and counted, but links nothing; other columns are ignored; empty tables work.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mfaccel.llm.common import cut
from mfaccel.plans.cuts import numbered

_MARKS = r"^((?:[ \t]?>)+)"
#: A line that only introduces the quote below it.
_INTRODUCES = r"(?i)^\s*(on .*wrote|.*(?:schrieb|écrit|escribió))\s*:\s*$"


def _key(text: Column) -> Column:
    plain = F.trim(F.regexp_replace(F.lower(text), r"\s+", " "))
    return F.when(F.length(plain) > 0, F.sha2(plain.cast("binary"), 256))


def _units(text: Column) -> Column:
    """Keys of a text with their sizes: the whole, its paragraphs, its lines."""
    parts = F.concat(F.array(text), F.split(text, r"\n[ \t]*\n"), F.split(text, r"\n"))
    return F.filter(F.transform(parts, lambda x: F.struct(_key(x).alias("key"), F.length(x).alias("size"))), lambda x: x["key"].isNotNull())


def parsed(messages: DataFrame, *, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """One row per message: conv, turn, role, own text, passages array<struct<level, at, text>>, max_level."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = messages.select(F.col(conv_col).cast("long").alias("conv"), F.col(turn_col).cast("long").alias("turn"), F.col(role_col).alias("role"), text.alias("text"))
    whole = rows.where("conv IS NOT NULL AND turn IS NOT NULL").groupBy("conv", "turn").agg(F.min(F.struct("text", "role")).alias("m")).select("conv", "turn", "m.role", "m.text")
    rows = whole.unionByName(rows.where("conv IS NULL OR turn IS NULL"))
    lines = F.transform(
        F.split("text", r"\r?\n"),
        lambda x: F.struct(
            F.length(F.regexp_replace(F.regexp_extract(x, _MARKS, 1), "[^>]", "")).alias("level"),
            F.regexp_replace(x, _MARKS + r"[ \t]?", "").alias("body"),
        ),
    )
    quoting = F.col("text").contains(">")
    made = _let(lines, lambda found: _let(F.transform(found, lambda x: x["level"]), lambda levels: _let(_starts(levels), lambda starts: _message(found, levels, starts))))
    rows = rows.withColumn("made", F.when(quoting, made))
    none = F.array().cast("array<struct<level:int,at:int,text:string>>")
    return rows.select(
        "conv", "turn", "role", F.when(quoting, F.col("made.own")).otherwise(F.col("text")).alias("own"),
        F.when(quoting, F.col("made.passages")).otherwise(none).alias("passages"), F.coalesce("made.max_level", F.lit(0)).alias("max_level"),
    )


def _let(value: Column, use) -> Column:
    """use(value), with the value computed once: nested lambdas see a variable, not the expression again for every element."""
    return F.get(F.transform(F.array(value), use), 0)


def _starts(levels: Column) -> Column:
    return F.filter(F.sequence(F.lit(0), F.size(levels) - 1), lambda i: (i == 0) | (F.get(levels, i) != F.get(levels, i - 1)))


def _message(found: Column, levels: Column, starts: Column) -> Column:
    """Own text, quoted passages and the highest level of a message that may quote."""

    def text(some: Column) -> Column:
        return F.array_join(F.transform(some, lambda x: x["body"]), "\n")

    runs = F.transform(
        starts,
        lambda s, k: F.struct(F.get(levels, s).alias("level"), s.alias("at"), text(F.slice(found, s + 1, F.coalesce(F.get(starts, k + 1), F.size(levels)) - s)).alias("text")),
    )
    kept = F.filter(found, lambda x, i: (x["level"] == 0) & ~(x["body"].rlike(_INTRODUCES) & (F.coalesce(F.get(levels, i + 1), F.lit(0)) > 0)))
    return F.struct(F.trim(text(kept)).alias("own"), F.filter(runs, lambda r: r["level"] > 0).alias("passages"), F.array_max(levels).alias("max_level"))


def links(messages: DataFrame) -> DataFrame:
    """(conv, turn, to_conv, to_turn, n_linked) of messages of parsed() that quote a known one."""
    named = messages.where("conv IS NOT NULL AND turn IS NOT NULL")
    quotes = named.where(F.size("passages") > 0).select("conv", "turn", F.explode("passages").alias("p"))
    quotes = quotes.select("conv", "turn", F.col("p.level").alias("level"), F.col("p.at").alias("at"), F.explode(_units(F.col("p.text"))).alias("u"))
    quotes = cut(quotes.select("conv", "turn", "level", "at", "u.key", "u.size"))
    wanted = quotes.select("key").distinct()
    originals = named.where("own <> ''").select("conv", "turn", F.explode(_units(F.col("own"))).alias("u")).select("conv", "turn", F.col("u.key").alias("key"))
    originals = originals.join(wanted, "key", "left_semi")
    near = originals.groupBy("key", "conv").agg(F.min("turn").alias("near_turn"))
    first = F.struct("conv", F.col("near_turn").alias("turn"))
    far = near.groupBy("key").agg(F.min(first).alias("far"))
    # The next conversation that has the key, for quotes in the first.
    second = near.join(far, "key").where(F.col("conv") != F.col("far.conv")).groupBy("key").agg(F.min(first).alias("next"))
    found = quotes.join(near, ["key", "conv"], "left").join(far.join(second, "key", "left"), "key", "left")
    here = F.when(F.col("near_turn") < F.col("turn"), F.struct("conv", F.col("near_turn").alias("turn")))
    there = F.when(F.col("far.conv") != F.col("conv"), F.col("far")).otherwise(F.col("next"))
    found = found.withColumn("to", F.coalesce(here, there)).where("to IS NOT NULL")
    best = F.min(F.struct((-F.col("size")).alias("s"), "level", "at", "to"))
    return found.groupBy("conv", "turn").agg(best.alias("b"), F.count_distinct("level", "at").alias("n_linked")).select("conv", "turn", F.col("b.to.conv").alias("to_conv"), F.col("b.to.turn").alias("to_turn"), "n_linked")


def roots(parents: DataFrame) -> DataFrame:
    """(conv, turn, root_conv, root_turn, depth) of messages that reply, from (conv, turn, to_conv, to_turn)."""
    state = cut(parents.select(F.struct("conv", "turn").alias("node"), F.struct(F.col("to_conv").alias("conv"), F.col("to_turn").alias("turn")).alias("top"), F.lit(1).cast("long").alias("depth"), F.least(F.struct("conv", "turn"), F.struct(F.col("to_conv").alias("conv"), F.col("to_turn").alias("turn"))).alias("least")))
    total, before = state.count(), -1
    for turn in range(64):
        if not total:
            break
        ahead = state.select(F.col("node").alias("top"), F.col("top").alias("top2"), F.col("depth").alias("depth2"), F.col("least").alias("least2"))
        state = cut(state.join(ahead, "top", "left").select("node", F.coalesce("top2", "top").alias("top"), (F.col("depth") + F.coalesce("depth2", F.lit(0))).alias("depth"), F.coalesce(F.least("least", "least2"), "least").alias("least"), F.isnotnull("top2").alias("more")))
        left = state.where("more").count()
        state = state.drop("more")
        if not left or (left == before and 2**turn > total):
            break
        before = left
    done = state.select("node", "top", "depth", "least")
    open_tops = done.select(F.col("node").alias("top"), F.lit(True).alias("ring"))
    done = done.join(open_tops, "top", "left")
    root = F.when(F.col("ring"), F.col("least")).otherwise(F.col("top"))
    return done.select("node.conv", "node.turn", root["conv"].alias("root_conv"), root["turn"].alias("root_turn"), F.when(F.col("ring"), F.lit(None)).otherwise(F.col("depth")).alias("depth"))


def linked(messages: DataFrame, **names: str) -> DataFrame:
    """One row per message: conv_id, turn, role, text without quotes, max_level, n_quotes, n_linked, reply_conv,
    reply_turn, root_conv, root_turn, depth (0 for a message that replies to none; null in a ring)."""
    own = parsed(messages, **names)
    to = cut(links(own))
    top = roots(to)
    out = own.join(to, ["conv", "turn"], "left").join(top, ["conv", "turn"], "left")
    return out.select(
        F.col("conv").alias("conv_id"), "turn", "role", F.col("own").alias("text"), F.col("max_level").cast("int").alias("max_level"),
        F.size("passages").alias("n_quotes"), F.coalesce("n_linked", F.lit(0)).alias("n_linked"),
        F.col("to_conv").alias("reply_conv"), F.col("to_turn").alias("reply_turn"),
        F.coalesce("root_conv", "conv").alias("root_conv"), F.coalesce("root_turn", "turn").alias("root_turn"),
        F.when(F.isnull("to_turn"), F.lit(0).cast("long")).otherwise(F.col("depth")).alias("depth"),
    )


def reply_ordered(linked_rows: DataFrame) -> DataFrame:
    """The rows of linked() in threads, every message after the one that it replies to, with `place`, the position from 1 in this order
    over all threads: by root, depth (a ring's last), conversation and turn. Ranges are sorted apart, so no task holds a long thread."""
    order = ["root_conv", "root_turn", F.col("depth").asc_nulls_last(), "conv_id", "turn", "role", "text"]
    return numbered(linked_rows, *order, name="place")
