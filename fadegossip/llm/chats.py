"""Cumulative-snapshot collapse of logged conversations, then rendering.

A log that stores a conversation after every reply holds each of its prefixes as a conversation. Each turn is
hashed; the hash of a prefix is the sum, over its turns, of the turn's hash scrambled with its place. Turns are
range-partitioned by conversation and turn, so that a conversation may run over partitions: running sums are made
within a partition, and what the partitions before it hold of its first conversation (one number set for each
partition) is added. A conversation goes if its length and hash are those of a proper prefix of another one;
equal conversations leave the one with the least id. Both are anti-joins of distinct (length, hash) rows, so a
first turn or a conversation that a third of the log shares is one row there.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadegossip.llm.frames import cut, shuffle_width, table
from fadegossip.llm.words import powers

# fixed values: the markup of a rendered turn
OPEN, CLOSE, END = "<|", "|>", "<|end|>"


def _ordered(turns: DataFrame) -> DataFrame:
    """Turns with two hashes each, sorted by conversation, turn, role and text over range partitions."""
    rows = turns.select("conv_id", "turn", F.xxhash64("role", "text", F.col("role").isNull(), F.col("text").isNull()).alias("a"), F.xxhash64(F.lit("second"), "text", "role").alias("b"))
    order = [F.col(c).asc_nulls_first() for c in ("conv_id", "turn", "a", "b")]
    return rows.repartitionByRange(shuffle_width(turns.sparkSession), *order).sortWithinPartitions(*order).withColumn("part", F.spark_partition_id())


BASES = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD1B54A32D192ED03))


def _running(batches):
    """(conv_id, part, fresh, k, a, b): place of each turn in its conversation and hashes of the prefix that ends there, as far as this partition knows.

    fresh: 0 for the conversation the partition begins with, more for later ones.
    """
    last, k0, carried, fresh, begun = None, 0, [np.uint64(0)] * 2, 0, False
    for batch in batches:
        n = batch.num_rows
        if not n:
            continue
        values = batch.column("conv_id").to_pylist()
        same = np.array([begun and values[0] == last, *(x == y for x, y in zip(values[1:], values))])
        start = np.maximum.accumulate(np.where(same, -1, np.arange(n)))  # -1: goes on from the batch before
        place = np.where(start >= 0, np.arange(n) - start, np.arange(n) + k0)
        sums = []
        for name, base, have in zip("ab", BASES, carried):
            total = np.cumsum(np.asarray(batch.column(name)).view(np.uint64) * powers(base, int(place.max()))[place], dtype=np.uint64)
            before = np.where(start > 0, total[np.maximum(start, 1) - 1], np.uint64(0))
            sums.append(np.where(start >= 0, total - before, total + have))
        number = fresh + np.cumsum(~same) - (0 if begun else 1)
        yield pa.RecordBatch.from_arrays([batch.column("conv_id"), batch.column("part"), pa.array(number, pa.int64()), pa.array(place + 1, pa.int64()), *[pa.array(x.view(np.int64)) for x in sums]], ["conv_id", "part", "fresh", "k", "a", "b"])
        last, k0, carried, fresh, begun = values[-1], int(place[-1]) + 1, [x[-1] for x in sums], int(number[-1]), True


def prefixes(turns: DataFrame) -> DataFrame:
    """(conv_id, k, a, b): for every turn its place and the hashes of the prefix that ends with it."""
    kind = turns.schema["conv_id"].dataType.simpleString()
    local = cut(_ordered(turns).mapInArrow(_running, f"conv_id {kind}, part int, fresh long, k long, a long, b long"))
    row = F.struct("fresh", "k", F.struct("conv_id").alias("of"), "a", "b")
    ends = sorted(local.groupBy("part").agg(F.min(row).alias("first"), F.max(row).alias("last")).collect(), key=lambda x: x.part)  # a row for each shuffle partition
    carry: dict[int, tuple[int, int, int]] = {}
    wrap = 2**64
    known, k, sums = None, 0, (0, 0)
    for end in ends:
        joined = known is not None and end.first["of"] == known
        if joined:
            carry[end.part] = (k, *sums)
        whole = end.last["fresh"] == 0
        own = (end.last["a"] % wrap, end.last["b"] % wrap)
        if joined and whole:
            sums = tuple((s + pow(int(base), k, wrap) * x) % wrap for s, x, base in zip(sums, own, BASES))
            k += end.last["k"]
        else:
            sums, k = own, end.last["k"]
        known = end.last["of"]

    def complete(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            part, fresh = np.asarray(batch.column("part")), np.asarray(batch.column("fresh"))
            k, sums = np.asarray(batch.column("k")).copy(), [np.asarray(batch.column(x)).view(np.uint64).copy() for x in "ab"]
            for p in np.unique(part[fresh == 0]).tolist():
                if p in carry:
                    at = (part == p) & (fresh == 0)
                    k0, *before = carry[p]
                    k[at] += k0
                    for x, base, have in zip(sums, BASES, before):
                        x[at] = np.uint64(have) + np.uint64(pow(int(base), k0, wrap)) * x[at]
            yield pa.RecordBatch.from_arrays([batch.column("conv_id"), pa.array(k), *[pa.array(x.view(np.int64)) for x in sums]], ["conv_id", "k", "a", "b"])

    return local.mapInArrow(complete, f"conv_id {kind}, k long, a long, b long")


def maximal(turns: DataFrame) -> DataFrame:
    """(conv_id, n_turns, n_copies) of the conversations that no other one continues, the least id of equal ones."""
    rows = cut(prefixes(turns))
    n = rows.groupBy("conv_id").agg(F.max("k").alias("n"))
    whole = F.max(F.struct("k", "a", "b")).alias("x")
    finals = rows.groupBy("conv_id").agg(whole).groupBy("x").agg(F.min(F.struct("conv_id")).alias("least"), F.count(F.lit(1)).alias("n_copies"))
    finals = finals.select("x.k", "x.a", "x.b", "least.conv_id", "n_copies")
    proper = rows.join(n.withColumnRenamed("conv_id", "c"), F.col("conv_id").eqNullSafe(F.col("c"))).where("k < n").select("k", "a", "b").distinct()
    return finals.join(proper, ["k", "a", "b"], "left_anti").select("conv_id", F.col("k").alias("n_turns"), "n_copies")


def _escaped(text):
    """Markup that a turn holds itself can't end or open one."""
    return F.replace(F.coalesce(text, F.lit("")), F.lit(OPEN), F.lit("< |"))


def collapse(turns: DataFrame) -> DataFrame:
    """turns (conv_id, turn, role, text) -> (conv_id, n_turns, n_copies, rendered) of the maximal conversations.

    Turns are in order of turn; turns with equal numbers are in a fixed order of their hashes. Null roles and texts
    differ from empty ones but are rendered empty; rows without a conv_id are one conversation. A rendered
    conversation is one value, so its turns meet in one task.
    """
    kept = maximal(turns)
    order = [F.col("turn"), F.xxhash64("role", "text", F.col("role").isNull(), F.col("text").isNull()), F.xxhash64(F.lit("second"), "text", "role")]
    piece = F.concat(F.lit(OPEN), _escaped(F.col("role")), F.lit(CLOSE + "\n"), _escaped(F.col("text")), F.lit(END + "\n"))
    pieces = turns.select(F.col("conv_id").alias("c"), F.struct(*[x.alias(f"o{i}") for i, x in enumerate(order)], piece.alias("piece")).alias("p"))
    chosen = pieces.join(kept, F.col("c").eqNullSafe(F.col("conv_id")))
    text = F.array_join(F.transform(F.array_sort(F.collect_list("p")), lambda x: x.piece), "")
    return chosen.groupBy("conv_id", "n_turns", "n_copies").agg(text.alias("rendered"))


def op8_chats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return collapse(table(spark, sf_dir, "conversations"))


#: Prefixes as strings instead of hashes, and every pair of equal length and prefix by a join.
ORACLE = """
WITH turns AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text,
         coalesce(role, chr(28)) || chr(31) || coalesce(text, chr(28)) || chr(30) AS body FROM conversations
), runs AS (
  SELECT conv_id, row_number() OVER w AS k, count(*) OVER (PARTITION BY conv_id) AS n,
         string_agg(body, '') OVER w AS prefix FROM turns
  WINDOW w AS (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)
), finals AS (
  SELECT n, prefix, min(conv_id) AS conv_id, count(*) AS n_copies FROM runs WHERE k = n GROUP BY n, prefix
), kept AS (
  SELECT f.conv_id, f.n, f.n_copies FROM finals f
  WHERE NOT EXISTS (SELECT 1 FROM runs r WHERE r.k < r.n AND r.k = f.n AND r.prefix = f.prefix)
)
SELECT k.conv_id, k.n AS n_turns, k.n_copies,
       string_agg('<|' || replace(t.role, '<|', '< |') || '|>' || chr(10) || replace(t.text, '<|', '< |') || '<|end|>' || chr(10), '' ORDER BY t.turn) AS rendered
FROM kept k JOIN turns t ON t.conv_id = k.conv_id GROUP BY 1, 2, 3
"""
