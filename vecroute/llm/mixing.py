"""Mixing sources to target weights by Pfair scheduling.

Each source's rows, in a seeded order, form blocks. With ``a`` of every ``Q`` slots
as target weight, block ``j`` is released at ``floor(jQ/a)`` and due at
``ceil((j+1)Q/a)``; slots go to the released block that is due first. As the weights
add up to one, every block meets its deadline, so after any number of slots each
source is less than one block away from its share.

The schedule repeats after ``Q`` slots. One period is computed as a single
expression over the small table of weights; a row's slot then follows from its rank
by arithmetic, so the exchange is of keys by (source, bucket) and no group is ever
larger than a period. All of it is DataFrame functions.

No row is dropped: when a source runs out its slots stay empty and the others keep
their relative weights; ``position`` closes the gaps.

Defined cases: null source is a source of its own; equal ids each keep their row; an
empty table gives no rows; a source missing from ``targets`` shares the weight that
is left; extra columns survive in ``mixed_order``, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from vecroute.llm.ranks import bucket_bits, bucket_counts, rank_in_stratum, seeded_key, stratum_key

SEED = 9
BLOCK_ROWS = 4
PERIOD = 256
TEMPERATURE = 0.5
#: A period has at most eight slots a source; it is broadcast up to so many sources, joined by exchange beyond.
BROADCAST_SOURCES = 1 << 12


def weights(counts: DataFrame, targets: dict[str, float] | None, temperature: float, period: int) -> DataFrame:
    """``stratum, rows, slots, period``: whole slots of a period by largest remainder, one at least.

    ``targets`` maps sources to weights; without it weight is the row count to the
    power ``temperature``. The period doubles until it holds four slots a source.
    """
    sizes = counts.groupBy("stratum").agg(F.sum("n").alias("rows"))
    if targets is None:
        raw = F.sqrt(F.col("rows")) if temperature == 0.5 else F.pow(F.col("rows").cast("double"), F.lit(temperature))
        sized = sizes.withColumn("raw", raw)
    else:
        if any(w <= 0 for w in targets.values()) or sum(targets.values()) > 1 + 1e-9:
            raise ValueError("target weights are positive and add up to one at most")
        given = F.lit(None).cast("double")
        for source, w in targets.items():
            given = F.when(F.col("stratum") == F.lit(f"s{source}"), F.lit(float(w))).otherwise(given)
        everywhere = Window.partitionBy(F.lit(1))
        rest = F.greatest(F.lit(1.0) - F.sum(given).over(everywhere), F.lit(1e-9)) / F.greatest(F.sum(given.isNull().cast("int")).over(everywhere), F.lit(1))
        sized = sizes.withColumn("raw", F.coalesce(given, F.coalesce(rest, F.lit(1.0))))
    everywhere = Window.partitionBy(F.lit(1))
    sources = F.count(F.lit(1)).over(everywhere)
    q = F.greatest(F.lit(period).cast("long"), F.pow(F.lit(2.0), F.ceil(F.log2(4 * sources))).cast("long"))
    exact = (F.col("period") - F.col("sources")) * F.col("raw") / F.sum("raw").over(everywhere)
    shared = sized.withColumns({"sources": sources, "period": q}).withColumn("exact", exact).withColumn("whole", F.floor("exact"))
    left = F.col("period") - F.col("sources") - F.sum("whole").over(everywhere)
    order = F.row_number().over(everywhere.orderBy((F.col("exact") - F.col("whole")).desc(), "stratum"))
    slots = 1 + F.col("whole") + (order <= left).cast("long")
    return shared.withColumn("slots", slots).select("stratum", "rows", "slots", "period")


def schedule(weighted: DataFrame) -> DataFrame:
    """``stratum, rows, slots, period, turn, slot``: each source's turns in one period, earliest deadline first.

    One row's work, whose cost grows with the square of the number of sources, not
    of rows: about a second for 1 000 of them.
    """
    one = weighted.groupBy().agg(F.array_sort(F.collect_list(F.struct("stratum", "rows", "slots", "period"))).alias("s")).where(F.size("s") > 0)
    far = "9223372036854775807L"
    put = lambda array, value: f"concat(slice({array}, 1, p), array({value}), slice({array}, p + 2, size(s)))"
    start = "named_struct('done', transform(s, x -> 0L), 'release', transform(s, x -> 0L), 'due', transform(s, x -> (x.period + x.slots - 1) div x.slots), 'picks', cast(array() as array<struct<at: int, turn: bigint>>))"
    # Per slot one look at all sources; then three numbers of the chosen one change.
    chosen = f"transform(array(zip_with(acc.release, acc.due, (r, d) -> if(r <= t, d, {far}))), e -> cast(array_position(e, array_min(e)) - 1 as int))"
    after = f"named_struct('done', {put('acc.done', 'j')}, 'release', {put('acc.release', '(j * s[p].period) div s[p].slots')}, 'due', {put('acc.due', '((j + 1) * s[p].period + s[p].slots - 1) div s[p].slots')}, 'picks', concat(acc.picks, array(named_struct('at', p, 'turn', j - 1))))"
    step = f"transform({chosen}, p -> transform(array(acc.done[p] + 1), j -> {after})[0])[0]"
    picks = F.expr(f"aggregate(sequence(0L, s[0].period - 1), {start}, (acc, t) -> {step}, acc -> acc.picks)")
    turns = one.select("s", F.posexplode(picks).alias("slot", "p"))
    return turns.select("slot", F.expr("s[p.at]").alias("w"), F.col("p.turn").alias("turn")).select("w.stratum", "w.rows", "w.slots", "w.period", "turn", F.col("slot").cast("long").alias("slot"))


def _scheduled(keyed: DataFrame, ties: list[Column], targets: dict[str, float] | None, temperature: float, block_rows: int, period: int) -> tuple[DataFrame, DataFrame]:
    total, sources = keyed.agg(F.count(F.lit(1)), F.count_distinct("stratum")).first()
    bits = bucket_bits(total)
    counts = bucket_counts(keyed, bits)
    weighted = weights(counts, targets, temperature, period)
    ranked = rank_in_stratum(keyed, counts, bits, ties, weighted.select("stratum", "slots", "period")).drop("stratum_rows")
    numbered = ranked.withColumn("block", F.expr(f"stratum_rank div {block_rows}"))
    numbered = numbered.withColumns({"lap": F.expr("block div slots"), "turn": F.expr("block % slots")})
    # A row per slot of a period; joined by exchange, a hot source's rows spread over its turns.
    turns = schedule(weighted).select("stratum", "turn", F.col("slot").alias("lap_slot"))
    out = numbered.join(F.broadcast(turns) if sources <= BROADCAST_SOURCES else turns, ["stratum", "turn"])
    out = out.withColumns({"slot": F.col("lap") * F.col("period") + F.col("lap_slot"), "release": F.expr("(block * period) div slots"), "deadline": F.expr("((block + 1) * period + slots - 1) div slots"), "in_block": F.expr(f"stratum_rank % {block_rows}")})
    return out, weighted


def mix(docs: DataFrame, targets: dict[str, float] | None = None, temperature: float = TEMPERATURE, block_rows: int = BLOCK_ROWS, period: int = PERIOD, seed: int = SEED) -> DataFrame:
    """``doc_id, source, block, release, deadline, slot, in_block, position`` of every row."""
    keyed = docs.select("doc_id", "source", stratum_key(F.col("source")).alias("stratum"), seeded_key(seed, F.col("doc_id")).alias("shuffle_key"))
    out, weighted = _scheduled(keyed, [F.col("doc_id")], targets, temperature, block_rows, period)
    inside = Window.partitionBy("lap").orderBy("slot", "in_block")
    # Rows of all sources in earlier laps: a whole-number function of their sizes.
    sizes = weighted.groupBy().agg(F.collect_list(F.struct("rows", "slots")).alias("sizes"))
    before = F.expr(f"aggregate(sizes, 0L, (acc, x) -> acc + least(x.rows, lap * x.slots * {block_rows}))")
    laps = out.groupBy("lap").agg(F.count(F.lit(1)).alias("_rows")).join(F.broadcast(sizes)).select("lap", before.alias("lap_start"))
    placed = out.withColumn("in_lap", F.row_number().over(inside)).join(laps, "lap").withColumn("position", F.col("lap_start") + F.col("in_lap") - 1)
    return placed.select("doc_id", "source", "block", "release", "deadline", "slot", F.col("in_block"), "position")


def mixed_order(docs: DataFrame, targets: dict[str, float] | None = None, temperature: float = TEMPERATURE, block_rows: int = BLOCK_ROWS, period: int = PERIOD, seed: int = SEED) -> DataFrame:
    """All rows and columns of ``docs``, range partitioned and sorted in the mixed order."""
    names = docs.columns
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("row"))
    keyed = packed.select("row", stratum_key(F.col("row.source")).alias("stratum"), seeded_key(seed, F.col("row.doc_id")).alias("shuffle_key"))
    out, _ = _scheduled(keyed, [F.xxhash64("row.text")], targets, temperature, block_rows, period)
    return out.select("row", "slot", "in_block").repartitionByRange(F.col("slot"), F.col("in_block")).sortWithinPartitions("slot", "in_block").select("row.*")
