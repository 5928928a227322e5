"""Chat formatting after the collapse of cumulative snapshots.

A logged conversation that is the beginning of a longer one is a snapshot of it. Each turn gets
a rolling hash of all turns up to it; a conversation whose last hash is also that of a turn
inside a longer one is dropped by an anti-join, and of equal ones the least conv_id stays.

One order holds in prefixes, in the rendered text and in the SQL: by turn, then role, then the md5
of the text, nulls last. Two turns are equal if role and text are, a null being equal to nulls only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Turns whose hashes roll within one task; blocks of them are chained by their sums.
BLOCK = 1024
#: In place of a null turn, which comes last.
_LAST = 1 << 62


def _rolled(rows: DataFrame) -> DataFrame:
    """(conv_id, pos, n, pa, pb): the 128-bit hash (pa, pb) of the first pos turns, of n."""
    text = F.unhex(F.md5(F.col("text").cast("binary")))
    turn = F.coalesce(F.col("turn").cast("long"), F.lit(_LAST))
    light = rows.select("conv_id", turn.alias("turn"), "role", text.alias("text"), F.floor(turn / BLOCK).cast("long").alias("block")).distinct()
    # hash functions pass over nulls, so these are told apart first
    told = [F.col("role").isNull(), F.col("text").isNull(), "role", "text"]
    light = light.select("*", F.xxhash64(*told).alias("a"), F.xxhash64(F.lit(1), *reversed(told)).alias("b"))
    key, order = ["conv_id", "block"], ["turn", F.asc_nulls_last("role"), F.asc_nulls_last("text")]
    inside = Window.partitionBy(*key).orderBy(*order)
    blocks, whole = Window.partitionBy("conv_id").orderBy("block"), Window.partitionBy("conv_id")
    before = blocks.rowsBetween(Window.unboundedPreceding, -1)
    size = light.groupBy(*key).agg(F.count("*").alias("m"))
    size = size.select(*key, F.coalesce(F.sum("m").over(before), F.lit(0)).alias("skip"), F.sum("m").over(whole).alias("n"))
    placed = light.withColumn("at", F.row_number().over(inside)).join(size, key).withColumn("pos", F.col("at") + F.col("skip"))
    placed = placed.select(*key, "n", "pos", F.xxhash64("pos", "a", "b").alias("ha"), F.xxhash64("b", "pos", "a").alias("hb"))
    total = placed.groupBy(*key).agg(F.bit_xor("ha").alias("ta"), F.bit_xor("hb").alias("tb"))
    total = total.select(*key, *(F.coalesce(F.bit_xor(f"t{c}").over(before), F.lit(0)).alias(f"o{c}") for c in "ab"))
    roll = Window.partitionBy(*key).orderBy("pos").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rolled = placed.withColumn("ra", F.bit_xor("ha").over(roll)).withColumn("rb", F.bit_xor("hb").over(roll)).join(total, key)
    return rolled.select("conv_id", "pos", "n", F.col("ra").bitwiseXOR(F.col("oa")).alias("pa"), F.col("rb").bitwiseXOR(F.col("ob")).alias("pb"))


def maximal(rows: DataFrame) -> DataFrame:
    """(conv_id, n) of the conversations of rows(conv_id, turn, role, text) that no longer one
    begins with; of equal ones the least conv_id. Equal rows are one turn; rows without conv_id are
    left out; an empty table gives none; other columns are ignored."""
    rows = rows.where(F.col("conv_id").isNotNull())
    prefix = _rolled(rows)
    full = prefix.where("pos = n").select("conv_id", "n", "pa", "pb")
    reach = prefix.groupBy("pa", "pb").agg(F.max("n").alias("longest"), F.min(F.when(F.col("pos") == F.col("n"), F.col("conv_id"))).alias("keeper"))
    # `keeper` is the least of those that end here
    snapshots = full.join(reach, ["pa", "pb"]).where("longest > n OR conv_id <> keeper").select("conv_id")
    return full.join(snapshots, "conv_id", "left_anti").select("conv_id", "n")


def rendered(turns: Column) -> Column:
    """Text of an array of structs (turn, role, text): a line for the role, then the text."""
    return F.array_join(F.transform(turns, lambda t: F.concat(F.lit("<|"), F.coalesce(t["role"], F.lit("unknown")), F.lit("|>\n"), F.coalesce(t["text"], F.lit("")), F.lit("\n"))), "")


def formatted(rows: DataFrame) -> DataFrame:
    """(conv_id, n_turns, rendered) of the maximal conversations of rows, as in maximal(). A null role is
    written as unknown, a null text as empty."""
    kept = maximal(rows)
    own = rows.select("conv_id", "turn", "role", "text").join(kept, "conv_id").distinct()
    place = [F.coalesce(F.col("turn").cast("long"), F.lit(_LAST)).alias("at"), F.col("role").isNull().alias("no_role"), "role", F.col("text").isNull().alias("no_text"), F.unhex(F.md5(F.col("text").cast("binary"))).alias("digest")]
    turns = own.groupBy("conv_id", "n").agg(F.array_sort(F.collect_list(F.struct(*place, "text"))).alias("turns"))
    return turns.select("conv_id", F.col("n").alias("n_turns"), rendered(F.col("turns")).alias("rendered"))


FORMATTED_SQL = """
WITH t AS (SELECT DISTINCT conv_id, turn, role, text FROM conversations WHERE conv_id IS NOT NULL),
c AS (
  SELECT conv_id, count(*) AS n_turns,
    list(struct_pack(role := role, text := text) ORDER BY turn NULLS LAST, role NULLS LAST, md5(text) NULLS LAST) AS turns,
    string_agg('<|' || coalesce(role, 'unknown') || '|>' || chr(10) || coalesce(text, '') || chr(10), '' ORDER BY turn NULLS LAST, role NULLS LAST, md5(text) NULLS LAST) AS rendered
  FROM t GROUP BY conv_id)
SELECT a.conv_id, a.n_turns, a.rendered FROM c a
WHERE NOT EXISTS (
  SELECT 1 FROM c b WHERE b.conv_id <> a.conv_id AND b.turns[1] IS NOT DISTINCT FROM a.turns[1]
    AND (b.n_turns > a.n_turns OR (b.n_turns = a.n_turns AND b.conv_id < a.conv_id))
    AND b.turns[1:a.n_turns] = a.turns)
"""
