"""Quotation linking: replies are joined to the messages they quote.

A line's quote level is its number of leading ">" marks. Quoted lines are normalised (case, blanks),
hashed and joined to equal unquoted lines: first within the conversation, to the latest earlier
message, else to the earliest message anywhere. A message's parent is the message that most of
its quoted lines at the outer level come from. Both sides are reduced to one row per line
hash before joins, so an opening that every conversation shares stays one row.

Parents chain into threads; roots and depths come from pointer doubling, in as many rounds as the
logarithm of the longest chain. Reply order is (root, depth, turn).

Defined results: null and empty texts quote nothing; messages with a null conversation or turn have no
links; rows repeated in the input are repeated in the result; a quote that matches nothing,
or only its own message, gives no parent; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rpqframe.llm.common import checkpoint, join_dealt, pick

MIN_CHARS = 8
QUOTED = r"^\s*(?:>\s*)+"


def quote_level(line: Column) -> Column:
    return F.regexp_count(F.regexp_extract(line, QUOTED, 0), F.lit(">"))


def normalised(line: Column) -> Column:
    return F.trim(F.lower(F.regexp_replace(F.regexp_replace(line, QUOTED, ""), r"\s+", " ")))


def message_lines(messages: DataFrame, min_chars: int = MIN_CHARS) -> DataFrame:
    """conv, turn, level, hash of each line that is long enough once normalised."""
    lines = messages.where("conv is not null and turn is not null and text is not null").select("conv", "turn", F.explode(F.split("text", "\n", -1)).alias("line"))
    norm = lines.select("conv", "turn", quote_level(F.col("line")).alias("level"), normalised(F.col("line")).alias("norm"))
    return norm.where(F.length("norm") >= min_chars).select("conv", "turn", "level", F.xxhash64("norm").alias("hash"))


def find_links(messages: DataFrame, min_chars: int = MIN_CHARS) -> DataFrame:
    """conv, turn, n_quoted, n_linked, parent (struct<conv,turn> or null) of each message that quotes."""
    lines = message_lines(messages, min_chars)
    quotes = checkpoint(lines.where("level >= 1").groupBy("conv", "turn", "hash").agg(F.min("level").alias("level")))
    asked = quotes.groupBy("hash").agg(F.count("*").alias("n"))
    # one row for each message and line, then only lines that are quoted somewhere
    own = lines.where("level = 0").select("conv", "turn", "hash").distinct().join(asked.select("hash"), "hash", "left_semi")
    own = checkpoint(own)
    # as of each quoting turn, the latest earlier turn of the conversation with that line
    order = Window.partitionBy("conv", "hash").orderBy("turn", "own").rowsBetween(Window.unboundedPreceding, -1)
    both = quotes.select("conv", "turn", "hash", "level", F.lit(0).alias("own")).unionByName(own.select("conv", "turn", "hash", F.lit(None).cast("int").alias("level"), F.lit(1).alias("own")))
    seen = both.withColumn("t", F.last(F.when(F.col("own") == 1, F.col("turn")), ignorenulls=True).over(order)).where("own = 0")
    near = seen.select("conv", "turn", "hash", "level", F.when(F.col("t").isNotNull(), F.struct("conv", F.col("t").alias("turn"))).alias("near"))
    anywhere = asked.join(own.groupBy("hash").agg(F.min(F.struct("conv", "turn")).alias("far")), "hash", "left")
    total = quotes.count()
    me = F.struct("conv", "turn")
    source = join_dealt(near, anywhere, ["hash"], "n", total)
    source = source.withColumn("source", F.coalesce("near", F.when(F.col("far") < me, F.col("far"))))
    votes = source.groupBy("conv", "turn", "source").agg(F.count("*").alias("n"), F.min("level").alias("level"))
    best = F.max(F.when(F.col("source").isNotNull(), F.struct((-F.col("level")).alias("l"), "n", "source")))
    return votes.groupBy("conv", "turn").agg(
        F.sum("n").alias("n_quoted"), F.coalesce(F.sum(F.when(F.col("source").isNotNull(), F.col("n"))), F.lit(0)).alias("n_linked"), best["source"].alias("parent")
    )


def thread_roots(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """conv, turn, root, depth of each linked message; parents always stand earlier, so chains end."""
    me = F.struct("conv", "turn")
    hops = checkpoint(links.where("parent is not null").select(me.alias("me"), F.col("parent").alias("up"), F.lit(1).cast("bigint").alias("depth")))
    for _ in range(max_rounds):
        nxt = hops.select(F.col("me").alias("up"), F.col("up").alias("up2"), F.col("depth").alias("depth2"))
        joined = checkpoint(hops.join(nxt, "up", "left").select("me", F.coalesce("up2", "up").alias("up"), (F.col("depth") + F.coalesce("depth2", F.lit(0))).alias("depth"), F.col("up2").isNotNull().alias("moved")))
        hops = joined.drop("moved")
        if joined.where("moved").isEmpty():
            return hops.select("me.conv", "me.turn", F.col("up").alias("root"), "depth")
    raise RuntimeError("a reply chain is longer than 2^max_rounds")


def reply_threads(messages: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", text_col: str = "text", min_chars: int = MIN_CHARS) -> DataFrame:
    """One row per message: its parent, thread root, depth, quote counts, and its text without quotes."""
    src = pick(messages, conv_col, turn_col, text_col).toDF("conv", "turn", "text")
    links = checkpoint(find_links(src, min_chars))
    placed = links.join(thread_roots(links), ["conv", "turn"], "left")
    own = F.array_join(F.filter(F.split("text", "\n", -1), lambda x: quote_level(x) == 0), "\n")
    out = src.withColumn("own_text", own).join(placed, ["conv", "turn"], "left")
    return out.select(
        F.col("conv").alias(conv_col), F.col("turn").alias(turn_col), "own_text",
        F.col("parent.conv").alias("parent_conv"), F.col("parent.turn").alias("parent_turn"),
        F.coalesce("root.conv", "conv").alias("root_conv"), F.coalesce("root.turn", "turn").alias("root_turn"), F.coalesce("depth", F.lit(0)).alias("depth"),
        F.coalesce("n_quoted", F.lit(0)).alias("n_quoted"), F.coalesce("n_linked", F.lit(0)).alias("n_linked"),
    )


def reply_order(threads: DataFrame) -> list[Column]:
    """Columns that order the messages of ``reply_threads``: thread by thread, replies after what they answer."""
    return [F.col(c) for c in ("root_conv", "root_turn", "depth")] + [F.col(threads.columns[0]), F.col(threads.columns[1])]


def conversations(messages: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text", min_chars: int = MIN_CHARS, most: int = 256) -> DataFrame:
    """Reply-ordered conversations without quotes: root_conv, root_turn, part, messages (array of conv, turn, role, text).

    A message that answers none starts a conversation of its own, but stays with the turns around it where a
    conversation has no links at all. Conversations longer than ``most`` messages go on in further parts, so no row
    grows with a conversation. Messages of which only quotes and blanks remain are left out; so are those with a
    null conversation or turn.
    """
    threads = reply_threads(messages, conv_col, turn_col, text_col, min_chars).dropDuplicates([conv_col, turn_col])
    roles = pick(messages, conv_col, turn_col, role_col).toDF("c", "t", "role").groupBy("c", "t").agg(F.min("role").alias("role"))
    linked = threads.groupBy(F.col(conv_col).alias("c0")).agg(F.max((F.col("depth") > 0).cast("int")).alias("linked"))
    rows = threads.where(F.col(conv_col).isNotNull() & F.col(turn_col).isNotNull() & (F.trim(F.regexp_replace("own_text", r"\s+", " ")) != ""))
    rows = rows.join(roles, (F.col(conv_col) == F.col("c")) & (F.col(turn_col) == F.col("t"))).join(linked, F.col(conv_col) == F.col("c0"))
    alone = (F.col("linked") == 0) & (F.col("depth") == 0)
    rows = rows.select(
        F.when(alone, F.col(conv_col)).otherwise(F.col("root_conv")).alias("root_conv"), F.when(alone, F.lit(None)).otherwise(F.col("root_turn")).alias("root_turn"),
        "depth", F.col(conv_col).alias("conv"), F.col(turn_col).alias("turn"), "role", F.col("own_text").alias("text"),
    )
    place = F.row_number().over(Window.partitionBy("root_conv", "root_turn").orderBy("depth", "conv", "turn")) - 1
    rows = rows.withColumn("place", place).withColumn("part", F.floor(F.col("place") / most).cast("int"))
    made = rows.groupBy("root_conv", "root_turn", "part").agg(F.sort_array(F.collect_list(F.struct("place", "conv", "turn", "role", "text"))).alias("m"))
    return made.select("root_conv", "root_turn", "part", F.transform("m", lambda x: F.struct(x["conv"].alias("conv"), x["turn"].alias("turn"), x["role"].alias("role"), x["text"].alias("text"))).alias("messages"))
