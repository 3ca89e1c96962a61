"""Mixing sources to target weights by Pfair scheduling, in DataFrame functions only.

A source's rows, in a fixed shuffled order, form blocks of `block_rows`.  A source of weight m gets m
blocks in every frame, as long as it has them; a frame has one slot for each block.  The j-th of the
c blocks that a source has in a frame of q slots is released at floor((j - 1) q / c) and due at
ceil(j q / c); every slot goes to the released block with the earliest deadline (ties to the first
source by name).  So at any slot every source is less than one block away from its share of the
frame, and exactly on it at the frame's end.  Frames change only when a source runs out, so a few
kinds of frames are simulated, each once; every kind's slots are then laid out over its frames in
pieces of `FRAMES` frames, and all rows find their block's slot by a join on source and block.

No source is numbered in one task: rows are counted by 4096 hash ranges of a source, ranges get
their offsets, and rows are numbered inside ranges.  No join is told to broadcast: Spark does so by
the sizes it measures.

Cases: a null source counts as the source of the empty name; a source without a given weight gets
`default` or, if weights are left out, max(1, floor(32 sqrt(n / largest n))) of its blocks; null ids
and repeated rows get places of their own (rows of one id in the order of a hash of all columns);
an empty table gives no rows; a result column whose name the rows already have gets a leading `_`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from levelindex import scratch
from levelindex.llm.common import column, free_name, row_hash

SPAN = 1 << 20
FRAMES = 1024


def simulated(c: Column, q: Column) -> Column:
    """Sources by slot of one frame: earliest deadline first among released blocks."""
    state = F.struct(F.transform(c, lambda x: F.lit(0).cast("long")).alias("done"), F.array().cast("array<long>").alias("picked"))

    def step(s: Column, t: Column) -> Column:
        def due(x: Column, i: Column) -> Column:
            done = F.element_at(s["done"], i + 1)
            ready = (done < x) & (F.floor(done * q / x) <= t)
            return F.when(ready, F.ceil((done + 1) * q / x) * SPAN + i)

        first = F.array_min(F.transform(c, due)) % SPAN
        return F.struct(F.transform(s["done"], lambda x, i: x + (i == first).cast("long")).alias("done"), F.concat(s["picked"], F.array(first)).alias("picked"))

    return F.aggregate(F.sequence(F.lit(0).cast("long"), q - 1), state, step, lambda s: s["picked"])


def weight_column(weights: dict[str, int] | None, default: int) -> Column:
    if weights is None:
        share = F.col("blocks") / F.max("blocks").over(Window.partitionBy())
        return F.greatest(F.lit(1), F.floor(F.lit(32) * F.sqrt(share))).cast("long")
    if any(w < 1 or w != int(w) for w in [*weights.values(), default]):
        raise ValueError("weights are whole numbers of blocks in a frame, one at least")
    out = F.lit(int(default))
    for name, w in weights.items():
        out = F.when(F.col("source") == name, F.lit(int(w))).otherwise(out)
    return out.cast("long")


def mix(docs: DataFrame, weights: dict[str, int] | None = None, default: int = 1, block_rows: int = 8, id_col: str = "doc_id", source_col: str = "source") -> DataFrame:
    """doc_id, source, block (of its source), slot and place of every row; `place` orders the mixture."""
    placed = schedule(docs.select(docs[id_col].alias("doc_id"), docs[source_col].alias("source")), weights, default, block_rows)
    return placed.select("doc_id", F.col("mix_source").alias("source"), "block", "slot", "place")


def timetable(sources: DataFrame) -> DataFrame:
    """mix_source, block, slot of every block of the sources (source, blocks, m)."""
    # kinds of frames: the number of whole frames of a source, and one more, are where the frames change
    full = F.floor(F.col("blocks") / F.col("m"))
    points = sources.select(F.explode(F.array(F.lit(0).cast("long"), full, full + 1)).alias("start")).distinct()
    ahead = Window.partitionBy().orderBy("start")
    kinds = points.withColumn("end", F.lead("start").over(ahead)).where(F.col("end").isNotNull())
    left = F.least(F.col("m"), F.col("blocks") - F.col("start") * F.col("m"))
    shares = sources.join(kinds, F.col("start") * F.col("m") < F.col("blocks")).withColumn("c", left)
    frames = shares.groupBy("start", "end").agg(F.array_sort(F.collect_list(F.struct("source", "c", "m"))).alias("members"), F.sum("c").alias("q"))
    base = F.coalesce(F.sum((F.col("end") - F.col("start")) * F.col("q")).over(ahead.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    frames = frames.withColumn("base", base)
    slots = frames.select("start", "end", "q", "base", "members", F.posexplode(simulated(F.col("members.c"), F.col("q"))).alias("pos", "who"))
    who = F.element_at("members", F.col("who").cast("int") + 1)
    taken = slots.select("start", "end", "q", "base", who["source"].alias("mix_source"), who["m"].alias("m"), F.col("pos").cast("long").alias("pos"))
    turns = taken.groupBy("start", "end", "q", "base", "mix_source", "m").agg(F.array_sort(F.collect_list("pos")).alias("turns"))
    turns = scratch.save(turns, "slots")
    pieces = turns.withColumn("from", F.explode(F.sequence("start", F.col("end") - 1, F.lit(FRAMES).cast("long")))).repartition("mix_source", "from")
    each = pieces.withColumn("frame", F.explode(F.sequence("from", F.least(F.col("from") + FRAMES, F.col("end")) - 1)))
    each = each.select("mix_source", "m", "frame", (F.col("base") + (F.col("frame") - F.col("start")) * F.col("q")).alias("first"), F.posexplode("turns").alias("turn", "pos"))
    return each.select("mix_source", (F.col("frame") * F.col("m") + F.col("turn")).alias("block"), (F.col("first") + F.col("pos")).cast("long").alias("slot"))


def schedule(rows: DataFrame, weights: dict[str, int] | None = None, default: int = 1, block_rows: int = 8) -> DataFrame:
    """The rows (which have doc_id and source) with mix_source, block, slot and place added."""
    own = [column(c) for c in rows.columns]
    key = F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")))
    packed = rows.select(F.struct(*own).alias("row"), F.col("doc_id").alias("id"), F.coalesce(F.col("source").cast("string"), F.lit("")).alias("mix_source"), key.alias("key"), row_hash(rows).alias("tie"))
    keyed = packed.withColumn("range", F.substring("key", 1, 3))
    counted = scratch.save(keyed.groupBy("mix_source", "range").agg(F.count("*").alias("n")), "ranges")
    before = Window.partitionBy("mix_source").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counted.select("mix_source", "range", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("offset"))

    sizes = counted.groupBy(F.col("mix_source").alias("source")).agg(F.ceil(F.sum("n") / block_rows).cast("long").alias("blocks"))
    placed = timetable(scratch.save(sizes.withColumn("m", weight_column(weights, default)), "sources"))

    numbered = keyed.withColumn("nth", F.row_number().over(Window.partitionBy("mix_source", "range").orderBy("key", "id", "tie")))
    numbered = numbered.join(offsets.hint("merge"), ["mix_source", "range"]).withColumn("at", F.col("offset") + F.col("nth") - 1)
    found = numbered.withColumn("block", F.floor(F.col("at") / block_rows).cast("long")).join(placed, ["mix_source", "block"])
    added = {"mix_source": F.col("mix_source"), "block": F.col("block"), "slot": F.col("slot"), "place": F.col("slot") * block_rows + F.col("at") % block_rows}
    return found.select(*[F.col("row").getField(c).alias(c) for c in rows.columns], *[v.alias(free_name(rows.columns, n)) for n, v in added.items()])


#: The same schedule for the default weights, in DuckDB's SQL.
ORACLE = """
WITH RECURSIVE keyed AS (
  SELECT doc_id, coalesce(source, '') AS source, md5(coalesce(doc_id::VARCHAR, '')) AS k FROM documents),
numbered AS (SELECT *, row_number() OVER (PARTITION BY source ORDER BY k, doc_id) - 1 AS at FROM keyed),
sized AS (SELECT source, ((count(*) + 7) // 8)::BIGINT AS blocks FROM keyed GROUP BY source),
sources AS (SELECT source, blocks, greatest(1, floor(32 * sqrt(blocks / max(blocks) OVER ())))::BIGINT AS m FROM sized),
points AS (SELECT DISTINCT unnest([0, blocks // m, blocks // m + 1]) AS start FROM sources),
spans AS (SELECT start, lead(start) OVER (ORDER BY start) AS stop FROM points),
frames AS (
  SELECT start, stop, list(source ORDER BY source) AS names, list(least(m, blocks - start * m) ORDER BY source) AS c,
         sum(least(m, blocks - start * m))::BIGINT AS q
  FROM sources, spans WHERE stop IS NOT NULL AND start * m < blocks GROUP BY start, stop),
based AS (SELECT *, coalesce(sum((stop - start) * q) OVER (ORDER BY start ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS base FROM frames),
sim AS (
  SELECT start, c, q, 0::BIGINT AS t, list_transform(c, lambda x: 0::BIGINT) AS done, NULL::BIGINT AS who FROM frames
  UNION ALL
  SELECT start, c, q, t + 1, list_transform(done, lambda d, i: d + CASE WHEN i = first THEN 1 ELSE 0 END), first
  FROM (SELECT *, list_min(list_transform(c, lambda x, i: CASE WHEN done[i] < x AND (done[i] * q) // x <= t
                THEN (((done[i] + 1) * q + x - 1) // x) * 1048576 + i END)) % 1048576 AS first
        FROM sim WHERE t < q)),
slots AS (
  SELECT s.start, b.names[s.who] AS source, s.t - 1 AS pos, row_number() OVER (PARTITION BY s.start, s.who ORDER BY s.t) - 1 AS turn
  FROM sim s JOIN frames b ON s.start = b.start WHERE s.who IS NOT NULL)
SELECT n.doc_id, n.source, (n.at // 8)::BIGINT AS block,
       (b.base + ((n.at // 8) // s.m - b.start) * b.q + l.pos)::BIGINT AS slot,
       ((b.base + ((n.at // 8) // s.m - b.start) * b.q + l.pos) * 8 + n.at % 8)::BIGINT AS place
FROM numbered n JOIN sources s ON n.source = s.source
JOIN based b ON (n.at // 8) // s.m >= b.start AND (n.at // 8) // s.m < b.stop
JOIN slots l ON l.start = b.start AND l.source = n.source AND l.turn = (n.at // 8) % s.m
"""
