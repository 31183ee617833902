"""Chat formatting by quotation linking.

A message's lines are parsed into nested quote levels (``>`` marks, as in mail and forums). Consecutive lines of one level
are a passage: its lines are joined, whatever way they were wrapped, and normalised. A passage is looked up by its lines
and sentences, and by the first and the last five words of it, so a quote that was wrapped again, or is a part of a
sentence, is found as well. Keys are compared as text. The other side are the messages' own (unquoted) passages: their
lines and sentences, and every run of five words. A passage is looked for first within the conversation, in the latest
earlier turn; one that is found nowhere there, among all conversations. A message replies to the turn that it quotes at
the lowest level, or else to the turn before it. Quotes and attribution lines are then dropped, and each conversation is
put in reply order: a branch that answers an older turn comes after the branch that it leaves.

Only built-in functions. Conversations are put in order by ranges, so a long one lies in many partitions. Originals are cut down to the keys that some quote asks for before they move, and equal keys of
a conversation are one row, so a line that everybody writes makes no group larger than the quotes of it.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from relayout.llm.shared import materialise, parts, table

MARK = r"^[\s>]*>"
#: How an attribution line ends, and what it holds, in four languages.
ATTRIBUTION = r"(?i)^\s*(on|am|le|el)\b.*\b(wrote|schrieb|a écrit|escribió)\s*:\s*$"


def normalised(line: Column) -> Column:
    """Lower case, quote marks gone, runs of anything but letters and digits one blank."""
    return F.trim(F.regexp_replace(F.lower(F.regexp_replace(line, MARK, "")), r"[^\p{L}\p{N}]+", " "))


#: Words of a run that identifies a quoted passage.
RUN = 5
#: Bits of the map of asked keys: 16 MB.
BITS = 1 << 27
#: Marks that don't occur in texts, between passages and between their parts.
CUT, PART = "\u0002", "\u0003"


def parse(messages: DataFrame) -> DataFrame:
    """messages with ``lines``: structs (at, level, raw), level 0 the message's own text; and ``passages``: structs (level,
    text, lines), runs of lines of one level, the text without quote marks and line breaks, lines the lines alone."""
    raw = F.split(F.regexp_replace(F.coalesce(F.col("text"), F.lit("")), f"[{CUT}{PART}]", " "), r"\r?\n")

    def line(x: Column, i: Column) -> Column:
        return F.struct(i.alias("at"), F.length(F.regexp_replace(F.regexp_extract(x, MARK, 0), r"[^>]", "")).alias("level"), x.alias("raw"))

    # one string in which each passage begins with its level: a pass over the lines, however many there are (a lambda that
    # looked into the column of lines would compute it again for each line)
    level = F.transform("lines", lambda x: x["level"])
    before = F.concat(F.array(F.lit(-1)), F.slice(level, 1, F.greatest(F.size(level) - 1, F.lit(1))))
    marked = F.zip_with("lines", before, lambda x, b: F.when(x.isNotNull(), F.concat(F.when(x["level"] != b, F.concat(F.lit(CUT), x["level"].cast("string"))).otherwise(F.lit("")), F.lit(PART), F.regexp_replace(x["raw"], MARK, ""))))
    blocks = F.filter(F.split(F.array_join(marked, ""), CUT), lambda x: x != "")

    def passage(x: Column) -> Column:
        parts = F.split(x, PART)
        rest = F.slice(parts, 2, F.size(parts))
        return F.struct(F.element_at(parts, 1).cast("int").alias("level"), F.array_join(rest, " ").alias("text"), rest.alias("lines"))

    out = messages.withColumn("lines", F.transform(raw, line))
    return out.withColumn("passages", F.transform(blocks, passage))


def keys_of(passage: Column, own: bool) -> Column:
    """The keys of a passage: its lines and sentences, and (weak) runs of words: all of an own passage, first and last of a
    quote."""
    units = F.transform(F.concat(passage["lines"], F.split(passage["text"], r"(?<=[.!?])\s+")), normalised)
    words = F.split(normalised(passage["text"]), " ")
    later = lambda k: F.slice(words, k + 1, F.greatest(F.size(words), F.lit(1)))
    runs = words
    for k in range(1, RUN):  # words side by side; a run that ends behind the last word is null
        runs = F.zip_with(runs, later(k), lambda x, y: F.concat(x, F.lit(" "), y))
    if not own:
        whole = F.filter(runs, lambda x: x.isNotNull())
        runs = F.array(F.get(whole, 0), F.try_element_at(whole, F.lit(-1)))
    some = lambda xs, weak: F.transform(F.array_distinct(F.filter(xs, lambda x: x.isNotNull() & (x != ""))), lambda x: F.struct(x.alias("key"), F.lit(weak).alias("weak")))
    return F.concat(some(units, 0), some(runs, 1))


def maybe_in(rows: DataFrame, asked: DataFrame) -> DataFrame:
    """rows without most of those whose key nobody asks for, before they move. asked: (key). The keys' hashes are bits of a map
    of BITS bits, whatever their number; a bit that two keys share only lets a row through that the join drops."""
    bit = lambda key: F.pmod(F.xxhash64(key), F.lit(BITS)) + 1
    marks = asked.select(bit(F.col("key")).alias("b")).groupBy(F.bitmap_bucket_number("b").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("b")).alias("map"))
    at = F.bitmap_bit_position(bit(F.col("key"))).cast("int")
    byte = F.conv(F.hex(F.substr("map", F.shiftright(at, 3) + 1, F.lit(1))), 16, 10).cast("int")
    is_set = F.expr("shiftright(_byte, _bit)").bitwiseAND(F.lit(1)) == 1
    near = rows.withColumn("_bucket", F.bitmap_bucket_number(bit(F.col("key")))).join(F.broadcast(marks), F.col("_bucket") == F.col("bucket"))  # at most BITS / 32768 rows of 4 KB
    return near.withColumns({"_byte": byte, "_bit": at.bitwiseAND(F.lit(7))}).filter(is_set).select(*rows.columns)


def link(messages: DataFrame) -> DataFrame:
    """One row a message: its columns, reply_to (turn, null for the first), reply_conv, n_quotes (quoted passages),
    n_linked (quoted passages found in an original), thread and position (reply order in the conversation), and clean (the
    text without quotes and attribution lines).

    messages: (conv_id, turn, role, text, ...). Null texts are empty messages; a null conv_id is one conversation, and
    null turns come first. Repeated (conv_id, turn) rows are each kept, and stand side by side. Of several originals
    the latest earlier turn of the conversation wins; across conversations the smallest (conv_id, turn). Columns named
    like the added ones are replaced. An empty table gives no rows.
    """
    added = ("reply_to", "reply_conv", "n_quotes", "n_linked", "thread", "position", "clean")
    own = [c for c in messages.columns if c not in added]
    parsed = parse(messages.select(*own))
    same = lambda a, b: a.eqNullSafe(b)

    quoted = parsed.select("conv_id", "turn", F.posexplode(F.filter("passages", lambda x: x["level"] > 0)).alias("passage", "x"))
    quoted = quoted.select("conv_id", "turn", "passage", F.col("x.level").alias("level"), F.explode(keys_of(F.col("x"), False)).alias("k")).groupBy("conv_id", "turn", "passage", "level", F.col("k.key").alias("key")).agg(F.min("k.weak").alias("weak"))
    asked = quoted.select("key").distinct()
    originals = parsed.select("conv_id", "turn", F.explode(F.filter("passages", lambda x: x["level"] == 0)).alias("x"))
    originals = originals.select("conv_id", "turn", F.explode(keys_of(F.col("x"), True)).alias("k")).select("conv_id", "turn", F.col("k.key").alias("key"))
    # (a semi-join would be pushed below the map's join, and everything would move)
    originals = maybe_in(originals, asked).join(asked, "key").select("conv_id", "turn", "key").distinct()

    # within the conversation: the last original before the quote, among rows of one line in one conversation
    both = quoted.select("conv_id", "turn", "key", "level", "passage", "weak", F.lit(1).alias("q")).unionByName(originals.select("conv_id", "turn", "key", *(F.lit(None).cast("int").alias(c) for c in ("level", "passage", "weak")), F.lit(0).alias("q")))
    earlier = Window.partitionBy("conv_id", "key").orderBy("turn").rangeBetween(Window.unboundedPreceding, -1)
    both = both.withColumn("turn", F.coalesce(F.col("turn").cast("long"), F.lit(-1)))
    here = both.withColumn("found", F.max(F.when(F.col("q") == 0, F.col("turn"))).over(earlier)).filter("q = 1")
    anywhere = originals.groupBy("key").agg(F.min(F.struct("conv_id", "turn")).alias("first"))
    there = here.join(anywhere, "key", "left")
    other = F.col("found").isNull() & F.col("first").isNotNull() & ~same(F.col("first.conv_id"), F.col("conv_id"))
    hits = there.select(
        "conv_id", "turn", "level", "passage", "weak", F.coalesce("found", F.when(other, F.col("first.turn"))).alias("to_turn"), F.when(F.col("found").isNotNull(), F.col("conv_id")).when(other, F.col("first.conv_id")).alias("to_conv"),
        F.col("found").isNotNull().alias("inside"),
    )
    # the lowest level, then the conversation's own turns, then lines and sentences before runs, then the latest
    best = hits.filter("to_turn IS NOT NULL").groupBy("conv_id", "turn").agg(
        F.count_distinct("passage").alias("n_linked"),
        F.min(F.struct("level", (~F.col("inside")).alias("outside"), "weak", (-F.col("to_turn")).alias("back"), "to_conv")).alias("b"),
    )
    best = best.select(F.col("conv_id").alias("_c"), F.col("turn").alias("_t"), "n_linked", (-F.col("b.back")).alias("_to"), F.col("b.to_conv").alias("_tc"), (~F.col("b.outside")).alias("_in"))

    keyed = parsed.withColumn("_turn", F.coalesce(F.col("turn").cast("long"), F.lit(-1)))
    rows = keyed.join(best, same(F.col("conv_id"), F.col("_c")) & (F.col("_turn") == F.col("_t")), "left")
    passage = F.size(F.filter("passages", lambda x: x["level"] > 0))
    kept = F.filter("lines", lambda x: (x["level"] == 0) & ~F.rlike(x["raw"], F.lit(ATTRIBUTION)))
    clean = F.when(F.col("text").isNotNull(), F.regexp_replace(F.array_join(F.transform(kept, lambda x: x["raw"]), "\n"), r"^\s+|\s+$", ""))
    rows = rows.select(*own, "_turn", "_to", "_tc", "_in", passage.alias("n_quotes"), F.coalesce("n_linked", F.lit(0)).alias("n_linked"), clean.alias("clean"), F.xxhash64("text").alias("_hash"))

    # in turn order, a long conversation over many partitions: what came before is looked up here and carried over
    rows = in_ranges(rows, ["conv_id", "_turn"], "turns")
    turns = Window.partitionBy("conv_id", "_part").orderBy("_turn")
    rows = with_carried(rows, F.max("_turn"), F.max)
    rows = rows.withColumn("_last", F.coalesce(F.max("_turn").over(turns.rangeBetween(Window.unboundedPreceding, -1)), "_carried"))
    # a branch begins at the first turn, and where a turn answers another than the one before it
    rows = rows.withColumn("_start", F.when(F.col("_last").isNull() | (F.coalesce(F.col("_in"), F.lit(False)) & (F.col("_to") != F.col("_last"))), F.col("_turn")))
    rows = with_carried(rows.drop("_carried"), F.max("_start"), F.max)
    # starts rise with turns, so the last one so far is the largest
    rows = rows.withColumn("thread", F.coalesce(F.max("_start").over(turns.rangeBetween(Window.unboundedPreceding, Window.currentRow)), "_carried"))
    rows = rows.withColumns({
        "reply_to": F.coalesce("_to", "_last"),
        "reply_conv": F.when(F.col("_to").isNotNull(), F.col("_tc")).when(F.col("_last").isNotNull(), F.col("conv_id")),
    })
    order = ["thread", "_turn", "_hash"]
    rows = in_ranges(rows.drop("_carried", "_part"), ["conv_id", *order], "replies")
    rows = with_carried(rows, F.count(F.lit(1)), F.sum)
    place = F.row_number().over(Window.partitionBy("conv_id", "_part").orderBy(*order))
    rows = rows.withColumn("position", (place + F.coalesce("_carried", F.lit(0))).cast("int"))
    return rows.select(*own, *added)


def in_ranges(rows: DataFrame, order: list[str], label: str) -> DataFrame:
    """rows, written in order over the session's partitions, with _part, the number of the range each lies in: a conversation
    of any length is cut into ranges. Equal keys share one."""
    return materialise(rows.repartitionByRange(parts(rows.sparkSession), *order).withColumn("_part", F.spark_partition_id()), label)


def with_carried(rows: DataFrame, value: Column, over: Callable[[Column], Column]) -> DataFrame:
    """rows with _carried: value of each earlier range of the conversation, combined; null where there is none. Only
    conversations that lie in several ranges have a row here: at most two ends and the ranges between, for each range."""
    each = rows.groupBy("conv_id", "_part").agg(value.alias("v"))
    whole = Window.partitionBy("conv_id")
    before = over(F.col("v")).over(whole.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1))
    each = each.select(F.col("conv_id").alias("_conv"), F.col("_part").alias("_at"), before.alias("_carried"), F.count(F.lit(1)).over(whole).alias("n")).filter("n > 1").drop("n")
    return rows.join(F.broadcast(each), rows["conv_id"].eqNullSafe(F.col("_conv")) & (F.col("_part") == F.col("_at")), "left").drop("_conv", "_at")


def render(linked: DataFrame) -> DataFrame:
    """A line of chat markup for each message: (conv_id, position, chat)."""
    role = F.coalesce(F.col("role"), F.lit("user"))
    return linked.select("conv_id", "position", F.concat(F.lit("<|"), role, F.lit("|>\n"), F.coalesce("clean", F.lit("")), F.lit("\n<|end|>")).alias("chat"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = link(table(spark, sf_dir, "conversations"))
    return found.select("conv_id", "turn", "role", "reply_to", "reply_conv", "n_quotes", "n_linked", "thread", "position", F.sha2(F.coalesce("clean", F.lit("")).cast("binary"), 256).alias("clean_sha256"))
