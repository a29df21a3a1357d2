"""Mixing sources to target weights (operator 2), by weighted fair queueing, in DataFrame operations only.

Each source's documents stand in one queue, in the order of a hash. A document's virtual finish time is the number of its
source's words served up to its end, over the source's weight; a source may be served ``cap`` times over, so a document
has one entry per turn. Entries are taken in order of virtual finish time until the budget is used up.

Served that way, by time x a source has had ``least(cap * size, weight * x)`` words. The targets are those sums at the time
where they add up to the budget, which is also where resharing the excess of capped sources by weight ends.

No window holds a whole source: queues are cut into hash ranges whose word sums are added up first, and the global order is
resolved by ranges of finish time, with an exact order only inside the range where the budget runs out.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from lexbridge.llm.scratch import Scratch

WORD = r"[^\x20\x09-\x0D]+"
ROWS_PER_RANGE = 5000


def _targets(sizes: DataFrame, weights: tuple[int, ...], cap: int, share: float) -> DataFrame:
    """skey, s, w, target, level: one row per source. The windows here run over sources, not documents."""
    cycle = F.array(*[F.lit(x) for x in weights])
    ranked = sizes.withColumn("w", F.element_at(cycle, (F.pmod(F.row_number().over(W.orderBy("skey")) - 1, F.lit(len(weights))) + 1).cast("int")))
    total = ranked.agg((F.sum("s") * F.lit(share)).alias("budget"))
    by_fill = W.orderBy(cap * F.col("s") / F.col("w"), "skey")
    filled = (
        ranked.crossJoin(F.broadcast(total))
        .withColumn("level", (F.col("budget") - (F.sum(cap * F.col("s")).over(by_fill) - cap * F.col("s"))) / F.sum("w").over(W.orderBy(F.desc(cap * F.col("s") / F.col("w")), F.desc("skey"))))
        .withColumn("free", cap * F.col("s") / F.col("w") >= F.col("level"))
    )
    level = filled.where("free").orderBy(cap * F.col("s") / F.col("w"), "skey").limit(1).select("level")
    return filled.drop("level", "free").crossJoin(F.broadcast(level)).select("skey", "s", "w", "level", "budget", F.when(cap * F.col("s") / F.col("w") < F.col("level"), (cap * F.col("s")).cast("double")).otherwise(F.col("w") * F.col("level")).alias("target"))


def _slot(at: Column, bits: int) -> Column:
    """The range of a virtual finish time; there is one range only where no source has a word."""
    return F.coalesce(F.floor(F.try_divide(at, F.col("level")) * F.lit(1 << bits)), F.lit(0))


def mix_sources(docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), cap: int = 3, share: float = 1.0) -> DataFrame:
    """Chooses how often each document goes into a mix of ``share`` times all words.

    ``docs`` has doc_id, text and source. Returns doc_id, size (words; a null text has none), source_size, target, taken
    (words the mix takes: 0 to ``cap`` times the size) and copies. Sources are ordered by code point with null last, and
    take ``weights`` in turn. Order inside a source follows md5 of the id, then the id, then the size, so reruns agree; rows
    that tie in all of these are alike. An empty table gives an empty result, and texts without any word are never taken. ``share`` must not exceed ``cap``.
    """
    scratch = Scratch(docs.sparkSession, "mixing")
    rows = docs.select(
        F.col("doc_id"),
        F.coalesce(F.concat(F.lit("0"), F.col("source")), F.lit("1")).alias("skey"),
        F.size(F.regexp_extract_all(F.coalesce("text", F.lit("")), F.lit(WORD), F.lit(0))).cast("long").alias("size"),
        # rows of null id are spread by a hash of their text
        F.conv(F.substring(F.md5(F.coalesce(F.col("doc_id").cast("string"), F.concat(F.lit("text "), F.coalesce("text", F.lit(""))))), 1, 15), 16, 10).cast("long").alias("r"),
    )
    rows = scratch.keep(rows, "rows")
    n = rows.count()
    bits = max(0, (n // ROWS_PER_RANGE).bit_length())
    rows = rows.withColumn("part", F.shiftright("r", 60 - bits))
    parts = scratch.keep(rows.groupBy("skey", "part").agg(F.sum("size").alias("ps")), "parts")
    targets = scratch.keep(_targets(parts.groupBy("skey").agg(F.sum("ps").alias("s")), weights, cap, share), "targets")
    before = parts.withColumn("before", F.sum("ps").over(W.partitionBy("skey").orderBy("part")) - F.col("ps")).drop("ps")
    inside = F.sum("size").over(W.partitionBy("skey", "part").orderBy("r", "doc_id", "size").rowsBetween(W.unboundedPreceding, 0))
    queued = rows.withColumn("inside", inside).join(before, ["skey", "part"]).join(targets, "skey").withColumn("served", F.col("before") + F.col("inside"))
    queued = scratch.keep(queued.select("doc_id", "skey", "size", "r", "s", "w", "level", "budget", "target", "served"), "queue")

    turns = queued.where("size > 0").select("*", F.explode(F.sequence(F.lit(0), F.lit(cap - 1))).alias("turn"))
    at = (F.col("turn") * F.col("s") + F.col("served")) / F.col("w")
    slot = _slot(at, bits)
    entries = turns.withColumn("at", at).withColumn("slot", slot)
    sums = entries.groupBy("slot").agg(F.sum("size").alias("words"), F.first("budget").alias("budget"))
    run = sums.withColumn("upto", F.sum("words").over(W.orderBy("slot")))
    edge = run.where("upto > budget").orderBy("slot").limit(1).select(F.col("slot").alias("edge"), (F.col("upto") - F.col("words")).alias("used"))
    edge = scratch.keep(edge, "edge")  # at most one row
    key = F.struct("at", "skey", "turn", "r", "doc_id")
    last = (
        entries.join(F.broadcast(edge), F.col("slot") == F.col("edge"))
        .withColumn("upto", F.col("used") + F.sum("size").over(W.orderBy("at", "skey", "turn", "r", "doc_id").rowsBetween(W.unboundedPreceding, 0)))
        .where("upto <= budget").agg(F.max(key).alias("last"))
    )
    cut = scratch.keep(last.join(F.broadcast(edge), how="left"), "cut")  # one row
    taken = F.lit(0)
    for turn in range(cap):
        here = (F.lit(turn) * F.col("s") + F.col("served")) / F.col("w")
        place = _slot(here, bits)
        own = F.struct(here.alias("at"), F.col("skey"), F.lit(turn).alias("turn"), F.col("r"), F.col("doc_id"))
        taken = taken + F.when((F.col("size") > 0) & (F.col("edge").isNull() | (place < F.col("edge")) | ((place == F.col("edge")) & F.coalesce(own <= F.col("last"), F.lit(False)))), 1).otherwise(0)
    out = queued.crossJoin(F.broadcast(cut)).withColumn("copies", taken)
    return out.select("doc_id", "size", F.col("s").alias("source_size"), "target", (F.col("size") * F.col("copies")).alias("taken"), "copies")


ORACLE = r"""
WITH rows AS (
  SELECT doc_id, coalesce('0' || source, '1') AS skey,
         len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
         ('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'text ' || coalesce(text, ''))), 1, 15))::BIGINT AS r
  FROM documents),
src AS (SELECT skey, sum(size)::BIGINT AS s, ((row_number() OVER (ORDER BY skey) - 1) % 3 + 1)::BIGINT AS w FROM rows GROUP BY skey),
tot AS (SELECT sum(s)::DOUBLE AS budget FROM src),
fill AS (
  SELECT skey, s, w, budget, (3 * s)::DOUBLE / w AS full_at,
         (budget - (sum(3 * s) OVER (ORDER BY (3 * s)::DOUBLE / w, skey) - 3 * s)) / sum(w) OVER (ORDER BY (3 * s)::DOUBLE / w DESC, skey DESC) AS lv
  FROM src, tot),
lev AS (SELECT arg_min(lv, (full_at, skey)) AS level FROM fill WHERE full_at >= lv),
tgt AS (SELECT skey, s, w, budget, CASE WHEN full_at < level THEN (3 * s)::DOUBLE ELSE w * level END AS target FROM fill, lev),
q AS (SELECT *, sum(size) OVER (PARTITION BY skey ORDER BY r, doc_id, size ROWS UNBOUNDED PRECEDING) AS served FROM rows JOIN tgt USING (skey)),
e AS (SELECT doc_id, size, budget, sum(size) OVER (ORDER BY (turn * s + served)::DOUBLE / w, skey, turn, r, doc_id ROWS UNBOUNDED PRECEDING) AS upto
      FROM q, (SELECT unnest([0, 1, 2]) AS turn) WHERE size > 0),
t AS (SELECT doc_id, count(*)::BIGINT AS copies FROM e WHERE upto <= budget GROUP BY doc_id)
SELECT doc_id, size, s AS source_size, target, (size * coalesce(copies, 0))::BIGINT AS taken, coalesce(copies, 0)::INTEGER AS copies
FROM q LEFT JOIN t USING (doc_id)
"""
