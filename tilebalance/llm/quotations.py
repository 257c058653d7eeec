"""Conversations in reply order without quotations, with DataFrame functions alone.

A line that begins with one or more ">" is quoted, once for each. A run of quoted lines of one level is a
passage. Quoted lines are normalised (lower case, white space to one space), hashed, and joined to the
unquoted lines of all messages. A passage comes from the message that has most of its lines: of the same
conversation and an earlier turn if there is one, the latest of them, or else of any other conversation, the
first of them. Passages of the same lines are one when other conversations are searched, and so are messages that have the same
of the quoted lines, so that very common lines make few pairs. A message replies to the source of its first passage of level 1 that was found in its
own conversation; messages without one begin a thread. The thread's turns on the way to a message
are its path, and paths sort a conversation into reply order.

Lines without letters or digits link nothing. Null texts are empty. Messages are told apart by
(conversation, turn); rows that repeat a pair stay, and share what is found for it. Rows with a null
conversation or turn link with nothing."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import stash

_MARK = r"^[ \t]*(?:>[ \t]?)+"


def _level(line: Column) -> Column:
    """Number of quotation marks at the start of a line."""
    return F.length(F.regexp_replace(F.regexp_extract(line, _MARK, 0), r"[^>]", ""))


def _norm(line: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(F.regexp_replace(line, _MARK, "")), r"\s+", " "))


def unquoted(text: Column) -> Column:
    """A text without its quoted lines and the blank lines around it."""
    kept = F.filter(F.split(F.coalesce(text.cast("string"), F.lit("")), "\n", -1), lambda x: ~F.rlike(x, F.lit(_MARK)))
    return F.regexp_replace(F.array_join(kept, "\n"), r"^(?:[ \t]*\n)+|(?:\n[ \t]*)+$", "")


def passages(messages: DataFrame, conversation: str = "conv_id", turn: str = "turn", text: str = "text") -> DataFrame:
    """(conv, turn, passage, level, lines, found, from_conv, from_turn) of each quoted passage; the source is null if none was found."""
    rows = messages.where(F.col(conversation).isNotNull() & F.col(turn).isNotNull()).select(F.col(conversation).alias("conv"), F.col(turn).alias("turn"), F.posexplode(F.split(F.col(text).cast("string"), "\n", -1)).alias("line", "raw")).distinct()
    rows = rows.select("conv", "turn", "line", _level(F.col("raw")).alias("level"), _norm(F.col("raw")).alias("norm"))
    quoted = rows.where("level > 0")
    # lines of one level in a row differ by the same from their rank among the lines of that level
    rank = F.row_number().over(Window.partitionBy("conv", "turn", "level").orderBy("line"))
    quoted = quoted.withColumn("run", F.col("line") - rank)
    quoted = quoted.withColumn("passage", F.min("line").over(Window.partitionBy("conv", "turn", "level", "run"))).drop("run")
    quoted = stash(quoted.select("conv", "turn", "passage", "level", "line", F.when(F.rlike("norm", F.lit(r"[\p{L}\p{N}]")), F.xxhash64("norm")).alias("h")), "quoted")
    asked = quoted.where("h is not null").select("h").distinct()
    own = rows.where("level = 0").where(F.rlike("norm", F.lit(r"[\p{L}\p{N}]"))).select("conv", "turn", F.xxhash64("norm").alias("h")).join(asked, "h", "left_semi")
    one = ["conv", "turn", "passage", "level"]
    here = own.select("h", "conv", F.col("turn").alias("from_turn")).distinct()
    votes = quoted.join(here, ["h", "conv"]).where("from_turn < turn").groupBy(*one, "from_turn").agg(F.count_distinct("line").alias("found"))
    near = votes.groupBy(*one).agg(F.min(F.struct(-F.col("found"), -F.col("from_turn"), F.col("conv").alias("from_conv"), "from_turn", "found")).alias("best"))
    near = stash(near.select(*one, "best.found", "best.from_conv", "best.from_turn"), "near")
    best = near.union(_elsewhere(quoted.where("h is not null").join(near, one, "left_anti"), own)).select(*one, F.struct("found", "from_conv", "from_turn").alias("best"))
    whole = quoted.groupBy("conv", "turn", "passage", "level").agg(F.count("*").alias("lines"))
    return whole.join(best, ["conv", "turn", "passage", "level"], "left").select("conv", "turn", "passage", "level", "lines", F.coalesce("best.found", F.lit(0)).alias("found"), "best.from_conv", "best.from_turn")


def _two_least(rows: DataFrame, by: str, order: tuple[str, ...]) -> DataFrame:
    """Of the rows of each `by` the first in the order, and the first of them of another conversation than that."""
    first = rows.groupBy(by).agg(F.min(F.struct(*order)).alias("a"))
    second = rows.join(first.select(by, F.col("a.conv").alias("_conv")), by).where("conv <> _conv").groupBy(by).agg(F.min(F.struct(*order)).alias("b"))
    return first.join(second, by, "left")


def _elsewhere(quoted: DataFrame, own: DataFrame) -> DataFrame:
    """(conv, turn, passage, level, found, from_conv, from_turn) of passages by the message of another conversation that has most of their lines."""
    one = ["conv", "turn", "passage", "level"]
    alike = stash(quoted.groupBy(*one).agg(F.sort_array(F.collect_list("h")).alias("hs")).withColumn("content", F.xxhash64("hs")), "alike")
    contents = alike.groupBy("content").agg(F.first("hs").alias("hs")).select("content", F.explode("hs").alias("h")).groupBy("content", "h").agg(F.count("*").alias("k"))
    # messages with the same of these lines get the same votes; the first, and the first of another conversation, stand for all
    asked = contents.select("h").distinct()
    held = own.join(asked, "h", "left_semi").groupBy("conv", "turn").agg(F.sort_array(F.collect_set("h")).alias("hs"))
    held = stash(held.select("conv", "turn", "hs", F.xxhash64("hs").alias("profile")), "held")
    kinds = held.groupBy("profile").agg(F.first("hs").alias("hs")).select("profile", F.explode("hs").alias("h"))
    two = _two_least(held, "profile", ("conv", "turn")).select("profile", F.explode(F.filter(F.array("a", "b"), lambda x: x.isNotNull())).alias("m")).select("profile", "m.conv", "m.turn")
    votes = contents.join(kinds, "h").groupBy("content", "profile").agg(F.sum("k").alias("found"))
    ranked = stash(votes.join(two, "profile").select("content", (-F.col("found")).alias("less"), "conv", "turn"), "votes")
    best = _two_least(ranked, "content", ("less", "conv", "turn"))
    m = F.when(F.col("a.conv") != F.col("conv"), F.col("a")).otherwise(F.col("b"))
    return alike.join(best, "content").select(*one, m.alias("m")).where("m is not null").select(*one, (-F.col("m.less")).alias("found"), F.col("m.conv").alias("from_conv"), F.col("m.turn").alias("from_turn"))


def reply_order(messages: DataFrame, conversation: str = "conv_id", turn: str = "turn", text: str = "text") -> DataFrame:
    """messages with clean_text, n_quoted, max_level, n_linked, parent_turn, thread_turn, depth and path."""
    found = stash(passages(messages, conversation, turn, text), "passages")
    replies = found.where("level = 1 and from_conv = conv").groupBy("conv", "turn").agg(F.min(F.struct("passage", "from_turn")).alias("p")).select("conv", "turn", F.col("p.from_turn").alias("parent"))
    facts = found.groupBy("conv", "turn").agg(F.sum("lines").alias("n_quoted"), F.max("level").alias("max_level"), F.count("from_turn").alias("n_linked"))
    # each round doubles the part of a path that is known
    paths = stash(replies.select("conv", "turn", F.col("parent").alias("up"), F.array("parent").alias("path")), "paths")
    while not paths.isEmpty():
        above = paths.select("conv", F.col("turn").alias("up"), F.col("up").alias("further"), F.col("path").alias("before"))
        longer = paths.join(above, ["conv", "up"], "left")
        if longer.where("further is not null").isEmpty():
            break
        paths = stash(longer.select("conv", "turn", F.coalesce("further", "up").alias("up"), F.when(F.col("before").isNotNull(), F.concat("before", "path")).otherwise(F.col("path")).alias("path")), "paths")
    named = facts.join(paths.select("conv", "turn", "path"), ["conv", "turn"], "left")
    keep = [F.col(f"m.{c}") for c in messages.columns if c not in ("clean_text", "n_quoted", "max_level", "n_linked", "parent_turn", "thread_turn", "depth", "path")]
    joined = messages.alias("m").join(named.alias("f"), (F.col(f"m.{conversation}") == F.col("f.conv")) & (F.col(f"m.{turn}") == F.col("f.turn")), "left")
    path = F.coalesce(F.col("f.path"), F.array().cast(found.select(F.array("turn").alias("t")).schema["t"].dataType))
    own = F.concat(path, F.array(F.col(f"m.{turn}")))
    zero = lambda c: F.coalesce(F.col(f"f.{c}"), F.lit(0)).cast("long").alias(c)
    return joined.select(*keep, unquoted(F.col(f"m.{text}")).alias("clean_text"), zero("n_quoted"), zero("max_level"), zero("n_linked"), F.try_element_at(path, F.lit(-1)).alias("parent_turn"), F.get(own, F.lit(0)).alias("thread_turn"), F.size(path).cast("long").alias("depth"), own.alias("path"))
