"""Quotation linking of conversations, by DataFrame functions only.

A line's quote level is the number of `>` before its text. Neighbouring lines of one level, not parted by a blank line, are a
passage; a passage is normalised (lower case, runs of white space to one blank, trimmed) and hashed. A quoted passage is linked
to the latest earlier message of its conversation that has it unquoted, as a paragraph or as one line; hashes find the message, the
normalised texts are compared. If there is none, each line and sentence of the passage is looked up in the same way; of the messages found so the
passage is linked to the one that has the most of its lines and sentences (of several, the latest). A message
replies to the message its outermost linked passage comes from (of several, the latest). Conversations are put in
reply order: `thread` is the first message up the chain of replies, and within conversation and thread messages go by turn, so
that an answer stands after what it answers; `position` is a message's place in its thread, from 1. `body` is the message without its
quoted lines, `chat` the body with its role; `conversations` puts the messages of a thread together.

Turns of one conversation that are equal are one message position: its rows keep their own bodies and are linked alike. A message without
conversation or turn has no place among others: it replies to nothing, is its own thread, and has no position. Null
texts are empty, null roles `unknown`. Repeated rows each get a row. Hot passages and long
conversations: passages are looked up through the latest earlier position in ranges of SPAN turns, and positions are counted by such ranges, so no
group of rows is sorted whole and no pairs of messages are made.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import materialise

#: Turns of one conversation whose uses of one passage are sorted together, and messages of a thread in one row of `conversations`.
SPAN = 1024
#: One class of characters without a group: Java's matcher goes through it in a loop, however many marks a line has.
MARK = r"^[ \t>]*"


def level(line: Column) -> Column:
    return F.length(F.translate(F.regexp_extract(line, MARK, 0), " \t", ""))


def passages(text: Column) -> Column:
    """Array of (level, lines) from a text; linear in its length."""
    lines = F.transform(F.split(F.regexp_replace(F.coalesce(text, F.lit("")), "\r\n?|\x0b|\x01|\x02", "\n"), "\n"), lambda x: F.struct(level(x).alias("level"), F.trim(F.regexp_replace(x, MARK, "")).alias("line")))
    shifted = F.concat(F.array(F.struct(F.lit(-1).alias("level"), F.lit("").alias("line"))), lines)
    # \x01 starts a passage, \x02 goes on with it.
    joined = F.zip_with(lines, F.slice(shifted, F.lit(1), F.size(lines)), lambda x, before: F.concat(F.when((x["level"] == before["level"]) & (x["line"] != "") & (before["line"] != ""), F.lit("\x02")).otherwise(F.concat(F.lit("\x01"), x["level"].cast("string"), F.lit("\x02"))), x["line"]))
    runs = F.filter(F.split(F.array_join(joined, ""), "\x01"), lambda x: x != "")
    return F.transform(runs, lambda r: F.struct(F.substring_index(r, "\x02", 1).cast("int").alias("level"), F.filter(F.slice(F.split(r, "\x02"), 2, 1 << 30), lambda x: x != "").alias("lines")))


def normal(text: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(text), r"\s+", " "))


def pieces(lines: Column) -> Column:
    """Normalised lines and sentences of a passage; sentences may run over lines."""
    runs = F.concat(lines, F.array(F.array_join(lines, " ")))
    parts = F.flatten(F.transform(runs, lambda x: F.split(F.regexp_replace(x, r"([.!?…]+[\"')\]”’]*)\s+|([。！？]+)\s*", "$1$2\x01"), "\x01")))
    return F.array_distinct(F.transform(F.filter(F.concat(lines, parts), lambda x: F.trim(x) != ""), normal))


def parse(turns: DataFrame) -> DataFrame:
    """conv_id, turn, role, body, quoted (array of level, normalised passage and pieces), own (normalised paragraphs and lines), own_pieces."""
    split = turns.select("conv_id", "turn", F.coalesce("role", F.lit("unknown")).alias("role"), passages(F.col("text")).alias("p"))
    own = F.filter("p", lambda x: (x["level"] == 0) & (F.size(x["lines"]) > 0))
    quoted = F.filter("p", lambda x: (x["level"] > 0) & (F.size(x["lines"]) > 0))
    paragraph = F.transform(own, lambda x: normal(F.array_join(x["lines"], " ")))
    single = F.transform(F.flatten(F.transform(own, lambda x: x["lines"])), normal)
    return split.select(
        "conv_id", "turn", "role",
        F.array_join(F.transform(own, lambda x: F.array_join(x["lines"], "\n")), "\n\n").alias("body"),
        F.transform(quoted, lambda x: F.struct(x["level"].alias("level"), normal(F.array_join(x["lines"], " ")).alias("t"), pieces(x["lines"]).alias("pieces"))).alias("quoted"),
        F.array_distinct(F.concat(paragraph, single)).alias("own"),
        F.array_distinct(F.flatten(F.transform(own, lambda x: pieces(x["lines"])))).alias("own_pieces"),
    )


def latest(wanted: DataFrame, have: DataFrame) -> DataFrame:
    """conv, at, h, t, source: for each wanted (conv, at, h, t) the latest earlier position of `have` with the same hash h and text t."""
    key = ["conv", "h", "t"]
    asked = wanted.select(*key).distinct()
    have = have.join(asked, key, "left_semi").distinct()
    marks = have.select(*key, "at", F.lit(True).alias("has")).unionAll(wanted.select(*key, "at", F.lit(False).alias("has")).distinct())
    marks = marks.groupBy(*key, "at").agg(F.max("has").alias("has")).withColumn("span", F.floor(F.col("at") / SPAN))
    # The last position of each range, carried over to later ranges; then the latest within the range.
    ranges = marks.groupBy(*key, "span").agg(F.max(F.when(F.col("has"), F.col("at"))).alias("last"))
    carried = ranges.withColumn("before", F.max("last").over(W.partitionBy(*key).orderBy("span").rowsBetween(W.unboundedPreceding, -1))).drop("last")
    inside = F.max(F.when(F.col("has"), F.col("at"))).over(W.partitionBy(*key, "span").orderBy("at").rowsBetween(W.unboundedPreceding, -1))
    return marks.withColumn("inside", inside).join(carried, [*key, "span"]).select("conv", "at", "h", "t", F.coalesce("inside", "before").alias("source")).where("source is not null")


def hashed(text: str) -> list[Column]:
    return [F.xxhash64(text).alias("h"), F.col(text).alias("t")]


def links(parsed: DataFrame) -> DataFrame:
    """conv, at, level, source: for each quoted passage the latest earlier position that has it, else the one that most of its pieces come from."""
    quoted = parsed.where(F.size("quoted") > 0).select("conv", "at", F.explode("quoted").alias("q")).select("conv", "at", F.col("q.level").alias("level"), F.col("q.t").alias("t"), F.col("q.pieces").alias("pieces"))
    wanted = quoted.select("conv", "at", "level", *hashed("t")).distinct()
    quoting = quoted.select("conv").distinct()  # other conversations have nothing to look up
    sources = parsed.join(quoting, "conv", "left_semi")
    whole = materialise(latest(wanted.drop("level").distinct(), sources.select("conv", "at", F.explode("own").alias("own")).select("conv", "at", F.xxhash64("own").alias("h"), F.col("own").alias("t"))), "whole-links")
    rest = quoted.withColumn("h", F.xxhash64("t")).join(whole, ["conv", "at", "h", "t"], "left_anti").select("conv", "at", "level", F.col("h").alias("passage"), F.explode("pieces").alias("t")).distinct().withColumn("h", F.xxhash64("t"))
    rest = materialise(rest, "quoted-pieces")
    said = sources.select("conv", "at", F.explode("own_pieces").alias("t")).select("conv", "at", *hashed("t"))
    by_piece = latest(rest.select("conv", "at", "h", "t").distinct(), said)
    passage = ["conv", "at", "level", "passage"]
    candidates = rest.join(by_piece, ["conv", "at", "h", "t"]).select(*passage, "source").distinct()
    asked = rest.select(*passage, "h", "t").join(candidates, passage)  # a candidate and a piece of its passage; never two messages of a conversation as such
    votes = asked.join(said.select("conv", F.col("at").alias("source"), "h", "t").distinct(), ["conv", "source", "h", "t"]).groupBy(*passage, "source").agg(F.count(F.lit(1)).alias("n"))
    most = votes.groupBy("conv", "at", "level", "passage").agg(F.max(F.struct("n", "source")).alias("best")).select("conv", "at", "level", F.col("best.source").alias("source"))
    return wanted.join(whole, ["conv", "at", "h", "t"]).select("conv", "at", "level", "source").unionAll(most)


def threads(parents: DataFrame) -> DataFrame:
    """(conv, at, thread) by pointer doubling over (conv, at, parent): as many rounds as the log of the longest chain."""
    now = materialise(parents.select("conv", "at", F.col("parent").alias("thread")), "threads")
    while True:
        up = now.select("conv", F.col("at").alias("thread"), F.col("thread").alias("further"))
        now = materialise(now.join(up, ["conv", "thread"], "left").select("conv", "at", F.coalesce("further", "thread").alias("thread"), F.col("further").isNotNull().alias("moved")), "threads")
        if now.where("moved").isEmpty():
            return now.drop("moved")
        now = now.drop("moved")


def places(threaded: DataFrame) -> DataFrame:
    """conv, at, position: places of distinct (conv, thread, at), counted by ranges of SPAN turns."""
    ranged = threaded.withColumn("span", F.floor(F.col("at") / SPAN))
    counts = ranged.groupBy("conv", "thread", "span").agg(F.count(F.lit(1)).alias("n"))
    before = F.coalesce(F.sum("n").over(W.partitionBy("conv", "thread").orderBy("span").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    own = F.row_number().over(W.partitionBy("conv", "thread", "span").orderBy("at"))
    return ranged.withColumn("own", own).join(counts.select("conv", "thread", "span", before.alias("before")), ["conv", "thread", "span"]).select("conv", "at", (F.col("own") + F.col("before")).alias("position"))


def link(turns: DataFrame) -> DataFrame:
    """conv_id, turn, role, reply_to, thread (turns), position, n_quotes, n_linked, body, chat; one row per row."""
    placed = F.col("conv_id").isNotNull() & F.col("turn").isNotNull()
    parsed = materialise(parse(turns).withColumns({"conv": F.col("conv_id").cast("string"), "at": F.col("turn").cast("bigint")}), "turns")
    known, loose = parsed.where(placed), parsed.where(~placed)
    found = links(known)
    outer = found.groupBy("conv", "at").agg(F.min(F.struct("level", (-F.col("source")).alias("s"))).alias("best"), F.count(F.lit(1)).alias("n_linked"))
    parents = materialise(outer.select("conv", "at", (-F.col("best.s")).alias("parent"), "n_linked"), "parents")
    rooted = parents.select("conv", "at", "parent", "n_linked").join(threads(parents), ["conv", "at"])
    # One row a position from here on, so that repeated turns meet a single row each.
    all_at = known.select("conv", "at").distinct().join(rooted, ["conv", "at"], "left").withColumn("thread", F.coalesce("thread", "at"))
    all_at = materialise(all_at, "positions")
    told = all_at.join(places(all_at.select("conv", "at", "thread")), ["conv", "at"])
    nothing = [F.lit(None).cast("bigint").alias("parent"), F.lit(None).cast("bigint").alias("n_linked"), F.col("at").alias("thread"), F.lit(None).cast("bigint").alias("position")]
    full = known.join(told, ["conv", "at"]).select(*parsed.columns, "parent", "n_linked", "thread", "position").unionAll(loose.select(*parsed.columns, *nothing))
    return full.select(
        "conv_id", "turn", "role", F.col("parent").alias("reply_to"), "thread", "position",
        F.size("quoted").cast("bigint").alias("n_quotes"), F.coalesce("n_linked", F.lit(0)).cast("bigint").alias("n_linked"), "body",
        F.concat(F.lit("<|"), "role", F.lit("|>\n"), "body", F.lit("\n")).alias("chat"),
    )


def in_reply_order(linked: DataFrame, parts: int) -> DataFrame:
    """The same rows, ranged and sorted by conversation, thread and place: the order in which they are written."""
    return linked.repartitionByRange(parts, "conv_id", "thread", "turn").sortWithinPartitions("conv_id", "thread", "turn")


def conversations(linked: DataFrame, span: int = SPAN) -> DataFrame:
    """conv_id, thread, part, n_rows, messages (position, turn, role, body) in reply order, and chat: the threads without quotes.

    A thread longer than `span` messages goes on in the next part. Rows without a place are left to `link`. Rows that repeat a position more often
    than `span` times go on in further rows of the same part."""
    placed = linked.where("position is not null")
    row = F.struct("position", "turn", "role", "body", "chat")
    keyed = placed.select("conv_id", "thread", F.floor((F.col("position") - 1) / span).alias("part"), row.alias("m"))
    # Repeats of a position are dealt by a hash of the message: equal messages are counted, not gathered.
    counted = keyed.groupBy("conv_id", "thread", "part", "m").agg(F.count(F.lit(1)).alias("n"))
    messages = F.sort_array(F.collect_list(F.struct("m.position", "m.turn", "m.role", "m.body", "m.chat", "n")))
    together = counted.groupBy("conv_id", "thread", "part").agg(messages.alias("messages"), F.sum("n").alias("n_rows"))
    chat = F.array_join(F.transform("messages", lambda x: x["chat"]), "").alias("chat")
    return together.select("conv_id", "thread", "part", "n_rows", F.transform("messages", lambda x: x.dropFields("chat")).alias("messages"), chat)


def op1_quote_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return in_reply_order(link(spark.read.parquet(f"{sf_dir}/conversations.parquet")), int(spark.conf.get("spark.sql.shuffle.partitions")))
