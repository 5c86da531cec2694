"""Preference data: conversations against themselves with another's last reply, the common turns once as prompt, then both masked completions.

No table holds labelled pairs, so they are made (``exchanged``): of each conversation the turns up to its last assistant
turn are the chosen side; on the rejected side that last reply is another conversation's, its neighbour in the order of
a hash. ``format_pairs`` takes any pairs of conversations: the longest common prefix is what precedes the first turn that
differs in role or text, or that one side lacks. It is rendered once; what follows is a completion of each side, whose
assistant turns are trained: ``mask`` lists the character ranges of the rendered text, end marks included, that carry loss.

A prompt or a completion is one row (``segment`` 0) up to ``SEGMENT`` turns; a longer one goes on in further rows, so that no
conversation is gathered without bound.

Defined cases: rows with null conv_id or turn are left out; of rows with one (conv_id, turn) the least (role, text)
counts; null role or text is empty; a conversation without assistant turn makes no pair, nor does the last one of an odd
number; if both replies are equal the pair gives its prompt alone; role marks inside texts are broken up, so that a text
cannot open or close a turn; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spanweave.session import stored

#: Turn numbers that share a row.
SEGMENT = 256


def turns(conversations: DataFrame) -> DataFrame:
    """conv_id, turn, role, text: one row each, without nulls."""
    rows = conversations.filter("conv_id is not null and turn is not null")
    said = F.struct(F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    return rows.groupBy("conv_id", "turn").agg(F.min(said).alias("x")).select("conv_id", "turn", "x.role", "x.text")


def neighbours(turns_: DataFrame) -> DataFrame:
    """(conv_id, last, donor, reply): each conversation's last assistant turn and the last reply of its neighbour.

    Ranks come without one task: ranges in the order of the hash, rows numbered in their range, the ranges' sizes summed up."""
    last = turns_.filter("role = 'assistant'").groupBy("conv_id").agg(F.max("turn").alias("last"), F.max_by("text", "turn").alias("reply"))
    order = [F.md5(F.col("conv_id").cast("string")), F.col("conv_id")]
    ranges = last.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("at", F.monotonically_increasing_id())
    ranges = stored(ranges.withColumn("part", F.shiftright("at", 33)), "ranked")
    sizes = stored(ranges.groupBy("part").agg(F.count(F.lit(1)).alias("n")), "ranges")  # a row per range
    earlier = F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    sizes = sizes.select("part", F.coalesce(earlier, F.lit(0)).alias("before"))
    rank = F.col("before") + F.col("at").bitwiseAND((1 << 33) - 1)
    ranked = ranges.join(F.broadcast(sizes), "part").withColumn("rank", rank)
    one = F.struct("rank", "conv_id", "last", "reply")
    two = ranked.groupBy(F.shiftright("rank", 1).alias("couple")).agg(F.min(one).alias("a"), F.max(one).alias("b"))
    two = two.filter("a.rank <> b.rank")
    side = lambda x, y: F.struct(F.col(f"{x}.conv_id"), F.col(f"{x}.last"), F.col(f"{y}.conv_id").alias("donor"), F.col(f"{y}.reply"))
    return two.select(F.explode(F.array(side("a", "b"), side("b", "a"))).alias("s")).select("s.*")


def exchanged(turns_: DataFrame, donors: DataFrame) -> DataFrame:
    """(pair_id, side, conv_id, turn, role, text) of both sides; ``conv_id``: whose words they are."""
    rows = turns_.join(donors.withColumnRenamed("conv_id", "pair_id"), F.col("conv_id") == F.col("pair_id")).filter("turn <= last")
    rows = rows.withColumn("side", F.explode(F.array(F.lit("chosen"), F.lit("rejected"))))
    swap = (F.col("side") == "rejected") & (F.col("turn") == F.col("last"))
    return rows.select(
        "pair_id", "side", F.when(swap, F.col("donor")).otherwise(F.col("conv_id")).alias("conv_id"), "turn", "role",
        F.when(swap, F.col("reply")).otherwise(F.col("text")).alias("text"),
    )


def rendered(role: Column, text: Column) -> tuple[Column, Column]:
    """(whole turn, where its text begins)."""
    safe = lambda c: F.replace(c, F.lit("<|"), F.lit("< |"))
    head = F.concat(F.lit("<|"), safe(role), F.lit("|>\n"))
    return F.concat(head, safe(text), F.lit("<|end|>\n")), F.length(head)


def masked_turns(sides: DataFrame) -> DataFrame:
    """pair_id, part (prompt, chosen, rejected), turn, conv_id, rendered, mask_start, mask_end: common turns once, the others by side."""
    said = F.struct("role", F.sha2("text", 256).alias("h"))
    same = sides.groupBy("pair_id", "turn").agg((F.count(F.lit(1)) == 2).alias("both"), (F.min(said) == F.max(said)).alias("equal"))
    differs = F.min(F.when(~(F.col("both") & F.col("equal")), F.col("turn"))).alias("_differ")
    prefix = stored(same.groupBy(F.col("pair_id").alias("_pair")).agg(differs), "prefix")
    rows = sides.join(prefix, F.col("pair_id") == F.col("_pair"))
    common = F.col("_differ").isNull() | (F.col("turn") < F.col("_differ"))
    rows = rows.withColumn("part", F.when(common, F.lit("prompt")).otherwise(F.col("side")))
    rows = rows.filter((F.col("part") != "prompt") | (F.col("side") == "chosen"))
    whole, head = rendered(F.col("role"), F.col("text"))
    trained = (F.col("part") != "prompt") & (F.col("role") == "assistant")
    return rows.select(
        "pair_id", "part", "turn", "conv_id", whole.alias("rendered"),
        F.when(trained, head).otherwise(0).cast("long").alias("mask_start"),
        F.when(trained, F.length(whole) - 1).otherwise(0).cast("long").alias("mask_end"),
    )


def format_pairs(sides: DataFrame) -> DataFrame:
    """pair_id, part, segment, turns, conv_id (of the last turn), text, mask: array of (first, end) character places."""
    each = F.struct("turn", "conv_id", "rendered", "mask_start", "mask_end")
    segment = F.floor(F.col("turn") / SEGMENT).cast("long").alias("segment")
    # at most SEGMENT distinct turn numbers of one side
    rows = masked_turns(sides).groupBy("pair_id", "part", segment).agg(F.sort_array(F.collect_list(each)).alias("t"))
    start = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<struct<first:bigint,end:bigint>>").alias("mask"))

    def add(acc: Column, t: Column) -> Column:
        one = F.struct((acc["at"] + t["mask_start"]).alias("first"), (acc["at"] + t["mask_end"]).alias("end"))
        mask = F.when(t["mask_end"] > 0, F.concat(acc["mask"], F.array(one))).otherwise(acc["mask"])
        return F.struct((acc["at"] + F.length(t["rendered"])).alias("at"), mask.alias("mask"))

    return rows.select(
        "pair_id", "part", "segment", F.size("t").cast("long").alias("turns"), F.element_at("t", -1)["conv_id"].alias("conv_id"),
        F.array_join(F.col("t.rendered"), "").alias("text"), F.aggregate("t", start, add)["mask"].alias("mask"),
    )


def from_exchanged_replies(conversations: DataFrame) -> DataFrame:
    """The prompt and the two completions of a pair per conversation; the mask as text ``first:end,first:end``."""
    said = stored(turns(conversations), "turns")
    done = format_pairs(exchanged(said, neighbours(said)))
    spans = F.transform("mask", lambda m: F.concat_ws(":", m["first"].cast("string"), m["end"].cast("string")))
    return done.withColumn("mask", F.array_join(spans, ","))


ORACLE = rf"""
WITH turns AS (SELECT conv_id, turn, min(struct_pack(role := coalesce(role, ''), text := coalesce(text, ''))) AS x
               FROM conversations WHERE conv_id IS NOT NULL AND turn IS NOT NULL GROUP BY conv_id, turn),
said AS (SELECT conv_id, turn, x.role AS role, x.text AS text FROM turns),
ends AS (SELECT conv_id, max(turn) AS last, arg_max(text, turn) AS reply FROM said WHERE role = 'assistant' GROUP BY conv_id),
ranked AS (SELECT *, row_number() OVER (ORDER BY md5(conv_id::VARCHAR), conv_id) - 1 AS rank FROM ends),
donors AS (SELECT a.conv_id AS pair_id, a.last, b.conv_id AS donor, b.reply FROM ranked a JOIN ranked b ON a.rank // 2 = b.rank // 2 AND a.rank <> b.rank),
own AS (SELECT d.*, s.* FROM said s JOIN donors d ON s.conv_id = d.pair_id WHERE turn <= last),
side AS (SELECT pair_id, 'chosen' AS side, conv_id, turn, role, text FROM own
  UNION ALL SELECT pair_id, 'rejected', CASE WHEN turn = last THEN donor ELSE conv_id END, turn, role, CASE WHEN turn = last THEN reply ELSE text END FROM own),
same AS (SELECT pair_id, turn, count(*) = 2 AND min(role) = max(role) AND min(text) = max(text) AS same FROM side GROUP BY pair_id, turn),
prefix AS (SELECT pair_id, min(CASE WHEN NOT same THEN turn END) AS differ FROM same GROUP BY pair_id),
part AS (SELECT side.*, CASE WHEN differ IS NULL OR turn < differ THEN 'prompt' ELSE side END AS part FROM side JOIN prefix USING (pair_id)),
line AS (SELECT *, '<|' || replace(role, '<|', '< |') || '|>' || chr(10) AS head, replace(text, '<|', '< |') || '<|end|>' || chr(10) AS body, turn // {SEGMENT} AS segment
  FROM part WHERE part <> 'prompt' OR side = 'chosen'),
placed AS (SELECT *, coalesce(sum(length(head || body)) OVER (PARTITION BY pair_id, part, segment ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM line)
SELECT pair_id, part, segment, count(*) AS turns, arg_max(conv_id, turn) AS conv_id, string_agg(head || body, '' ORDER BY turn) AS text,
  coalesce(string_agg(CASE WHEN part <> 'prompt' AND role = 'assistant' THEN (before + length(head))::BIGINT || ':' || (before + length(head || body) - 1)::BIGINT END, ',' ORDER BY turn), '') AS mask
FROM placed GROUP BY pair_id, part, segment
"""
