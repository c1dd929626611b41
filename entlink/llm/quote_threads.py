"""Chat formatting by quotation linking, in DataFrame functions only.

A line's quote level is the number of ``>`` marks before it.  Runs of quoted
lines of one level are passages.  A passage, as a whole and line by line, is
normalised (case, white space) and hashed, and joined to the earliest message
of the conversation whose own text, as a whole or by line, has the hash; a
whole passage counts one more than its lines.  The message with most hits is
the one quoted, the earliest of equals.  A message's parent is what its
passages of the least linked level quote.

Hashes of own lines are reduced to one row per conversation and hash before
the join, so a line that stands in very many messages makes no more pairs than
one that stands in few.  Roots and depths come from pointer jumping over the
messages that have a parent, in rounds that double the reach.

The result is the conversation without quoted lines (and without the line that
introduces a quotation), in reply order: threads by their first message, then
by depth, so that a reply comes after what it replies to.

Defined results: a null text counts as empty; a null conversation id is a
conversation of its own; equal turns are ordered by role and text; repeated
rows are messages of their own; quotes of no earlier message are removed and
link nothing; an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from entlink.operators.ordering import ranked
from entlink.storage import materialize

MARKS = r"^(?:[ \t]?>)+"
INTRODUCTION = r"^On .{1,200} wrote:[ \t]*$"


def level_of(line: Column) -> Column:
    return F.length(F.regexp_replace(F.regexp_extract(line, MARKS, 0), r"[^>]", ""))


def normal(line: Column) -> Column:
    """Line as it is hashed: lower case, runs of white space as one blank."""
    return F.trim(F.regexp_replace(F.lower(line), r"\s+", " "))


def own_lines(text: Column) -> Column:
    return F.filter(F.split(text, "\n"), lambda x: ~(x.rlike(MARKS) | x.rlike(INTRODUCTION)))


def _hash(text: Column) -> Column:
    return F.when(text != "", F.xxhash64(text))


def quoted_units(messages: DataFrame) -> DataFrame:
    """``(msg, conv, level, hash, weight)`` of every quoted passage and line; messages have ``msg``, ``conv``, ``text``."""
    lines = messages.where(F.col("text").rlike("(?m)" + MARKS)).select("msg", "conv", F.posexplode(F.split("text", "\n")).alias("no", "line"))
    lines = lines.withColumn("level", level_of(F.col("line")))
    one = Window.partitionBy("msg").orderBy("no")  # a message's own lines
    starts = F.when(F.col("level") != F.coalesce(F.lag("level").over(one), F.lit(-1)), 1).otherwise(0)
    runs = lines.withColumn("start", starts).withColumn("run", F.sum("start").over(one)).where("level > 0")
    runs = runs.withColumn("clean", normal(F.regexp_replace("line", MARKS, "")))
    single = runs.select("msg", "conv", "level", _hash(F.col("clean")).alias("hash"), F.lit(1).alias("weight"))
    joined = F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("no", "clean"))), lambda x: x["clean"]), " ")
    whole = runs.groupBy("msg", "conv", "level", "run").agg(joined.alias("clean"))
    whole = whole.select("msg", "conv", "level", _hash(F.trim(F.regexp_replace("clean", r"\s+", " "))).alias("hash"), F.lit(1).alias("weight"))
    return single.unionByName(whole).where("hash is not null")


def own_units(messages: DataFrame, wanted: DataFrame) -> DataFrame:
    """``(conv, hash, origin)``: the earliest message whose own text or line has a wanted hash."""
    own = messages.select("msg", "conv", own_lines(F.col("text")).alias("lines"))
    units = F.array_distinct(F.concat(F.transform("lines", normal), F.array(normal(F.array_join("lines", "\n")))))
    rows = own.select("msg", "conv", F.explode(units).alias("unit")).select("msg", "conv", _hash(F.col("unit")).alias("hash"))
    found = rows.join(wanted.select("conv", "hash").distinct(), ["conv", "hash"], "left_semi")
    return found.groupBy("conv", "hash").agg(F.min("msg").alias("origin"))


def parents(messages: DataFrame) -> DataFrame:
    """``(msg, parent)`` of every message that quotes an earlier one."""
    quoted = materialize(quoted_units(messages), "quoted-units")
    hits = quoted.join(own_units(messages, quoted), ["conv", "hash"]).where("origin < msg")
    votes = hits.groupBy("msg", "level", "origin").agg(F.sum("weight").alias("n"))
    best = votes.groupBy("msg").agg(F.min(F.struct("level", (-F.col("n")).alias("less"), "origin")).alias("best"))
    return materialize(best.select("msg", F.col("best.origin").alias("parent")), "quote-parents")


def roots(links: DataFrame) -> DataFrame:
    """``(msg, root, depth)`` of every message with a parent, by doubling jumps; a parent is always an earlier message."""
    now = links.select("msg", F.col("parent").alias("root"), F.lit(1).cast("long").alias("depth"))
    while True:
        ahead = now.select(F.col("msg").alias("root"), F.col("root").alias("then"), F.col("depth").alias("more"))
        then = now.join(ahead, "root", "left").select(
            "msg", F.coalesce("then", "root").alias("root"), (F.col("depth") + F.coalesce("more", F.lit(0))).alias("depth"), F.col("then").isNotNull().alias("moved")
        )
        then = materialize(then, "quote-roots")
        moved = then.where("moved").head(1)
        now = then.drop("moved")
        if not moved:
            return now


def reply_ordered(
    conversations: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text"
) -> DataFrame:
    """One row per message: conversation, turn, role, ``position`` in reply order, ``parent_turn``, ``depth``,
    ``quoted_lines`` and ``clean_text``."""
    slim = conversations.select(
        F.col(conv_col).alias("conv"), F.col(turn_col).alias("turn"), F.col(role_col).alias("role"), F.coalesce(F.col(text_col), F.lit("")).alias("text")
    )
    messages, _ = ranked(slim, ["conv", "turn", "role", "text"], "msg", "messages")
    links = parents(messages.withColumn("conv", F.coalesce(F.col("conv").cast("string"), F.lit(""))))
    origin = messages.select(F.col("msg").alias("parent"), F.col("turn").alias("parent_turn"))
    known = links.join(roots(links), "msg").join(origin, "parent").select("msg", "root", "depth", "parent_turn")
    kept = own_lines(F.col("text"))
    # Blank lines that stood around a quotation go with it.
    clean = F.regexp_replace(F.array_join(kept, "\n"), r"^\n+|\n+$", "")
    quotes = F.size(F.filter(F.split("text", "\n"), lambda x: x.rlike(MARKS)))
    rows = messages.join(known, "msg", "left").select(
        "conv", "turn", "role", "msg", F.coalesce("root", "msg").alias("root"), F.coalesce("depth", F.lit(0)).alias("depth"), "parent_turn",
        quotes.alias("quoted_lines"), F.when(quotes > 0, clean).otherwise(F.col("text")).alias("clean_text"),
    )
    placed, _ = ranked(rows, ["conv", "root", "depth", "msg"], "place", "reply-order")
    first = placed.groupBy(F.col("conv").alias("of")).agg(F.min("place").alias("first"))
    return placed.join(first, F.col("conv").eqNullSafe(F.col("of"))).select(
        F.col("conv").alias(conv_col),
        F.col("turn").alias(turn_col),
        F.col("role").alias(role_col),
        (F.col("place") - F.col("first")).alias("position"),
        "parent_turn",
        "depth",
        "quoted_lines",
        "clean_text",
    )
