"""Preference formatting of conversation pairs, in DataFrame functions only.

``preference_pairs`` takes chosen and rejected conversations by pair id, as turns. It
finds the longest common prefix of turns (role and text, null-safe), renders it once as
the prompt, and emits the two completions with masks: code point spans of the rendered
completion that a loss counts (texts of assistant turns; the markup and other roles do
not count).

``neighbour_pairs`` makes pairs out of plain conversations: each is chosen against the
next conversation (by id) that opens with the same turn. A hot opening never meets in
one task: ids of any type that has an order are cut into blocks by their range (sampled
bounds, so blocks are of near equal size; written once, so they stay as they are),
neighbours are found inside a block, and only the first and last conversation of each
(opening, block) meet across blocks. The last of an
opening, and any with an opening of its own, is compared with a copy of itself whose
final assistant turn is replaced by its previous assistant turn (empty text if none):
a stale reply as the rejected one.

Defined cases: turns are ordered by number, then role, then text; repeated turns stay;
a null turn number comes first; null roles and texts render as empty; a pair with one
side missing has an empty completion there; equal conversations have the whole as
prompt and two empty completions. Extra columns are not read. A null conversation id
forms a conversation of its own.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import materialise, table

# The markup of a rendered turn.
OPEN, MIDDLE, CLOSE = "<|im_start|>", "\n", "<|im_end|>\n"
TRAINED_ROLE = "assistant"
TURN = "array<struct<turn:bigint,role:string,text:string>>"


def gather_turns(turns: DataFrame, key: str = "conv_id") -> DataFrame:
    """One row a conversation: its key and ``turns``, in order."""
    turn = F.struct(F.col("turn").cast("long").alias("turn"), F.col("role").cast("string").alias("role"), F.col("text").cast("string").alias("text"))
    return turns.groupBy(turns[key].alias(key)).agg(F.array_sort(F.collect_list(turn)).cast(TURN).alias("turns"))


def _same(a: Column, b: Column) -> Column:
    return a["role"].eqNullSafe(b["role"]) & a["text"].eqNullSafe(b["text"])


def prefix_length(chosen: Column, rejected: Column) -> Column:
    """Turns that both begin with."""
    both = F.arrays_zip(chosen.alias("c"), rejected.alias("r"))
    short = F.least(F.size(chosen), F.size(rejected))
    differs = F.array_position(F.transform(F.slice(both, 1, short), lambda x: ~_same(x["c"], x["r"])), True)
    return F.when(short < 1, 0).when(differs > 0, differs - 1).otherwise(short).cast("int")


def _rendered(turn: Column) -> Column:
    return F.concat(F.lit(OPEN), F.coalesce(turn["role"], F.lit("")), F.lit(MIDDLE), F.coalesce(turn["text"], F.lit("")), F.lit(CLOSE))


def render(turns: Column) -> Column:
    return F.array_join(F.transform(turns, _rendered), "")


def mask(turns: Column) -> Column:
    """Spans [start, end) of assistant texts in the rendered turns."""
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,end:int>>").alias("out"))

    def step(state: Column, t: Column) -> Column:
        begin = state["at"] + F.length(F.coalesce(t["role"], F.lit(""))) + len(OPEN) + len(MIDDLE)
        end = begin + F.length(F.coalesce(t["text"], F.lit("")))
        counted = t["role"].eqNullSafe(F.lit(TRAINED_ROLE)) & (end > begin)
        span = F.struct(begin.alias("start"), end.alias("end"))
        return F.struct((end + len(CLOSE)).alias("at"), F.when(counted, F.concat(state["out"], F.array(span))).otherwise(state["out"]).alias("out"))

    return F.aggregate(turns, start, step, lambda s: s["out"])


def format_pairs(pairs: DataFrame, chosen: str = "chosen", rejected: str = "rejected") -> DataFrame:
    """Replaces two columns of turns by prompt_turns, prompt, and both completions with masks."""
    c, r = (F.coalesce(F.col(x), F.array().cast(TURN)) for x in (chosen, rejected))
    kept = [x for x in pairs.columns if x not in (chosen, rejected)]
    cut = pairs.select(*kept, c.alias("__c"), r.alias("__r")).withColumn("prompt_turns", prefix_length(F.col("__c"), F.col("__r")))
    n = F.col("prompt_turns")
    tail = lambda x: F.slice(F.col(x), n + 1, F.greatest(F.size(x) - n, F.lit(0)))
    return cut.select(
        *kept,
        "prompt_turns",
        render(F.slice(F.col("__c"), 1, n)).alias("prompt"),
        render(tail("__c")).alias("chosen"),
        mask(tail("__c")).alias("chosen_mask"),
        render(tail("__r")).alias("rejected"),
        mask(tail("__r")).alias("rejected_mask"),
    )


def preference_pairs(chosen: DataFrame, rejected: DataFrame, key: str = "pair_id") -> DataFrame:
    """From two tables of turns (key, turn, role, text)."""
    c = gather_turns(chosen, key).withColumnRenamed("turns", "chosen")
    r = gather_turns(rejected, key).withColumnRenamed("turns", "rejected")
    joined = c.join(r.withColumnRenamed(key, "__key"), F.col(key).eqNullSafe(F.col("__key")), "full_outer")
    return format_pairs(joined.select(F.coalesce(key, "__key").alias(key), "chosen", "rejected"))


def stale_reply(turns: Column) -> Column:
    """The conversation with its last assistant turn's text replaced by the one before it."""
    spoken = F.filter(turns, lambda t: t["role"].eqNullSafe(F.lit(TRAINED_ROLE)))
    place = F.transform(turns, lambda t: t["role"].eqNullSafe(F.lit(TRAINED_ROLE)))
    last = F.size(turns) - F.array_position(F.reverse(place), True)
    earlier = F.when(F.size(spoken) > 1, F.element_at(spoken, -2)["text"]).otherwise(F.lit(""))
    swapped = F.transform(turns, lambda t, i: F.struct(t["turn"].alias("turn"), t["role"].alias("role"), F.when(i == last, earlier).otherwise(t["text"]).alias("text")))
    return F.when(F.size(spoken) == 0, F.slice(turns, 1, F.greatest(F.size(turns) - 1, F.lit(0)))).otherwise(swapped)


def neighbours(conversations: DataFrame, blocks: int | None = None) -> DataFrame:
    """(conv_id, next_id): the next conversation by id with the same opening turn, null for the last.

    ``blocks``: ranges of ids; the session's shuffle partitions if not given.
    """
    opening = F.element_at("turns", 1)
    keyed = conversations.select("conv_id", F.xxhash64(F.coalesce(opening["role"], F.lit("\0")), F.coalesce(opening["text"], F.lit("\0"))).alias("opening"))
    ranged = keyed.repartitionByRange(blocks, "conv_id") if blocks else keyed.repartitionByRange("conv_id")
    keyed = materialise(ranged.withColumn("block", F.spark_partition_id()))
    inside = keyed.withColumn("next_id", F.lead("conv_id").over(Window.partitionBy("opening", "block").orderBy("conv_id")))
    # one row an (opening, block): an opening meets in one task with as many rows as there are blocks
    ends = keyed.groupBy("opening", "block").agg(F.min("conv_id").alias("first"), F.max("conv_id").alias("last"))
    across = ends.withColumn("after", F.lead("first").over(Window.partitionBy("opening").orderBy("block"))).select("last", "after")
    linked = inside.join(across, inside["conv_id"] == across["last"], "left")
    return linked.select("conv_id", F.coalesce("next_id", "after").alias("next_id"))


def neighbour_pairs(turns: DataFrame) -> DataFrame:
    """Formatted pairs, one row a conversation: conv_id, rejected_id (null: stale reply), and the columns of ``format_pairs``."""
    conversations = gather_turns(turns)
    known = neighbours(conversations.filter("conv_id is not null"))
    other = conversations.select(F.col("conv_id").alias("rejected_id"), F.col("turns").alias("other"))
    named = conversations.join(known.withColumnRenamed("conv_id", "__id"), F.col("conv_id") == F.col("__id"), "left")
    # conversations without a neighbour go by their own id, so that they do not meet in one task
    partner = (F.coalesce("next_id", "conv_id") == F.col("rejected_id")) & F.col("next_id").isNotNull()
    paired = named.join(other, partner, "left")
    return format_pairs(paired.select("conv_id", "rejected_id", F.col("turns").alias("chosen"), F.when(F.col("rejected_id").isNull(), stale_reply(F.col("turns"))).otherwise(F.col("other")).alias("rejected")))


def op9_preference_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neighbour_pairs(table(spark, sf_dir, "conversations"))
