"""Mixing sources to target weights by Pfair scheduling.

Each source's documents, in a hash-shuffled order, are cut into blocks.  With whole
weights a_s that sum to a period Q, block j of a source is released in slot
floor(j Q / a_s) and due by slot ceil((j + 1) Q / a_s); in every slot the released block
with the earliest deadline runs.  The schedule of one period repeats, so only that
pattern is simulated; the slot of each block then follows by arithmetic in the plan.
At every slot each source is less than one block away from its exact share.  When a
source runs out, a new phase starts with the weights of the others.

Nothing is dropped or repeated.  Ranks within a source come from counts of (source,
cell) groups of bounded size, so a source with a third of all rows is numbered by many
tasks.  The plan that is broadcast has one row a source: at most ``max_sources``
(checked), with the block patterns of its phases.

Defined results: a null source is a source of its own; sources without a given weight
use ``default_weight``; rows with equal ids are numbered as separate rows; an empty
table gives an empty result; other columns pass through ``mix`` untouched.
"""

from __future__ import annotations

import heapq

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import load, materialize, shuffle_width

BLOCK, PERIOD, CELL_ROWS, MAX_SOURCES = 64, 1000, 8192, 2000


def whole_weights(weights: dict, period: int) -> dict:
    """Whole numbers of at least 1 that sum to the period (grown if there are more sources), by largest remainder."""
    period = max(period, len(weights))
    total = sum(weights.values())
    exact = {s: w / total * period for s, w in weights.items()}
    out = {s: max(1, int(x)) for s, x in exact.items()}
    order = sorted(exact, key=lambda s: (-(exact[s] - int(exact[s])), str(s)))
    while (gap := period - sum(out.values())) != 0:
        for s in order if gap > 0 else reversed(order):
            if gap == 0:
                break
            if gap > 0 or out[s] > 1:
                out[s] += 1 if gap > 0 else -1
                gap += -1 if gap > 0 else 1
    return out


def edf_pattern(whole: dict) -> dict:
    """The slots of each source's blocks within one period."""
    q = sum(whole.values())
    keys = sorted(whole, key=str)
    coming = [(0, -(-q // whole[s]), n, 0) for n, s in enumerate(keys)]  # release, deadline, source, block
    heapq.heapify(coming)
    ready: list[tuple[int, int, int]] = []
    slots: dict = {s: [] for s in keys}
    for t in range(q):
        while coming and coming[0][0] <= t:
            _, due, n, j = heapq.heappop(coming)
            heapq.heappush(ready, (due, n, j))
        due, n, j = heapq.heappop(ready)
        a = whole[keys[n]]
        slots[keys[n]].append(t)
        if j + 1 < a:
            heapq.heappush(coming, ((j + 1) * q // a, -(-(j + 2) * q // a), n, j + 1))
    return slots


def phases(blocks: dict, weights: dict, period: int = PERIOD) -> list[dict]:
    """Phases until all blocks are placed: base slot, length, and per source its first block, share and pattern."""
    left, done, base, out = dict(blocks), dict.fromkeys(blocks, 0), 0, []
    left = {s: n for s, n in left.items() if n > 0}
    while left:
        whole = whole_weights({s: weights[s] for s in left}, period)
        pattern, q = edf_pattern(whole), sum(whole.values())
        length = min((n - 1) // whole[s] * q + pattern[s][(n - 1) % whole[s]] + 1 for s, n in left.items())
        out.append({"base": base, "length": length, "period": q, "sources": {s: (done[s], whole[s], pattern[s]) for s in left}})
        for s in list(left):
            used = length // q * whole[s] + sum(x < length % q for x in pattern[s])
            done[s] += used
            left[s] -= used
            if left[s] == 0:
                del left[s]
        base += length
    return out


def _ranked(docs: DataFrame, counts: DataFrame, cells: int, seed: int) -> DataFrame:
    offsets = counts.withColumn("_before", F.sum("_n").over(Window.partitionBy("source").orderBy("_cell").rowsBetween(Window.unboundedPreceding, -1)))
    tagged = docs.withColumn("_order", F.xxhash64("doc_id", F.lit(seed))).withColumn("_cell", F.pmod("_order", F.lit(cells)))
    numbered = tagged.withColumn("_rank", F.row_number().over(Window.partitionBy("source", "_cell").orderBy("_order", "doc_id")))
    o = offsets.select(F.col("source").alias("_s"), F.col("_cell").alias("_c"), F.coalesce("_before", F.lit(0)).alias("_before"))
    return numbered.join(o, numbered["source"].eqNullSafe(o["_s"]) & (numbered["_cell"] == o["_c"])).withColumn("_seq", F.col("_before") + F.col("_rank") - 1).drop("_s", "_c", "_before", "_rank", "_order", "_cell")


def positions(docs: DataFrame, weights: dict | None = None, *, block: int = BLOCK, period: int = PERIOD, temperature: float = 0.5,
              default_weight: float | None = None, cell_rows: int = CELL_ROWS, max_sources: int = MAX_SOURCES, seed: int = 7) -> DataFrame:
    """``docs`` with block, slot and position columns; without weights a source weighs its row count to the power ``temperature``."""
    spark = docs.sparkSession
    keys = docs.select("source", "doc_id")
    total = keys.count()
    cells = max(1, -(-total // cell_rows))
    counts = materialize(keys.groupBy("source", F.pmod(F.xxhash64("doc_id", F.lit(seed)), F.lit(cells)).alias("_cell")).agg(F.count(F.lit(1)).alias("_n")), "mix-counts")
    sizes = counts.groupBy("source").agg(F.sum("_n").alias("n")).limit(max_sources + 1).collect()
    if len(sizes) > max_sources:
        raise ValueError(f"more than {max_sources} sources")
    sizes = {r["source"]: r["n"] for r in sizes}
    given = weights or {}
    if weights is None:
        share = {s: n**temperature for s, n in sizes.items()}
    else:
        spare = default_weight if default_weight is not None else min(given.values(), default=1.0)
        share = {s: float(given.get(s, spare)) for s in sizes}
    plan = phases({s: -(-n // block) for s, n in sizes.items()}, share, period)
    short, rows = [], []
    for s, n in sizes.items():
        steps = [(p["sources"][s][0], p["base"], p["period"], p["sources"][s][1], p["sources"][s][2]) for p in plan if s in p["sources"]]
        rows.append((s, steps))
        if n % block:
            first, base, q, a, slots = steps[-1]
            i = (n - 1) // block - first
            short.append((base + i // a * q + slots[i % a], block - n % block))
    table = spark.createDataFrame(rows, "_s string, _steps array<struct<first:bigint,base:bigint,period:bigint,share:bigint,slots:array<int>>>")
    missing = F.array(*[F.struct(F.lit(s).cast("bigint").alias("slot"), F.lit(g).cast("bigint").alias("gap")) for s, g in short]) if short else None
    ranked = _ranked(docs, counts, cells, seed)
    placed = ranked.join(F.broadcast(table), ranked["source"].eqNullSafe(table["_s"])).withColumn("block", F.floor(F.col("_seq") / block))
    step = F.element_at(F.filter("_steps", lambda x: x["first"] <= F.col("block")), -1)
    placed = placed.withColumn("_step", step).withColumn("_i", F.col("block") - F.col("_step.first"))
    slot = F.col("_step.base") + F.floor(F.col("_i") / F.col("_step.share")) * F.col("_step.period") + F.element_at("_step.slots", (F.pmod("_i", F.col("_step.share")) + 1).cast("int"))
    placed = placed.withColumn("slot", slot.cast("bigint"))
    gaps = F.aggregate(F.filter(missing, lambda x: x["slot"] < F.col("slot")), F.lit(0).cast("bigint"), lambda acc, x: acc + x["gap"]) if missing is not None else F.lit(0)
    return placed.withColumn("position", F.col("slot") * block + F.pmod("_seq", F.lit(block)) - gaps).drop("_s", "_steps", "_step", "_i", "_seq")


def mix(docs: DataFrame, weights: dict | None = None, **options) -> DataFrame:
    """``docs``, all columns, physically in mixed order: partition after partition by position."""
    # the input's own columns travel in a struct, so that clashing names do no harm
    held = docs.select("doc_id", "source", F.struct(*docs.columns).alias("_row"))
    placed = positions(held, weights, **options)
    parts = shuffle_width(docs.sparkSession)
    total = docs.count()
    where = F.least(F.floor(F.col("position") * parts / F.lit(max(1, total))), F.lit(parts - 1)).cast("int")
    return placed.repartitionById(parts, where).sortWithinPartitions("position").select("_row.*")


def stretches(docs: DataFrame, rows: int, name: str = "stretch") -> DataFrame:
    """``docs`` with the number of the stretch of ``rows`` rows, along the physical order that ``mix`` gave, that each row is in.

    In files that order is (number of the file, row in it), which Spark does not keep when it
    reads them: large files come first.  Rows that come from no file count by partition.
    """
    try:
        placed = docs.select("*", F.struct(F.col("_metadata.file_name").alias("part"), F.col("_metadata.row_index").alias("at")).alias("_place"))
    except AnalysisException:
        key = F.monotonically_increasing_id()
        placed = docs.select("*", F.struct(F.lpad(F.shiftright(key, 33).cast("string"), 10, "0").alias("part"), key.bitwiseAND(F.lit((1 << 33) - 1)).alias("at")).alias("_place"))
    # one row a file: the driver adds them up
    counts = sorted(((r["part"], r["n"]) for r in placed.groupBy("_place.part").agg((F.max("_place.at") + 1).alias("n")).collect()), key=lambda c: (len(c[0].split("-")[1]) if c[0].startswith("part-") else 0, c[0]))
    before, offsets = 0, []
    for part, n in counts:
        offsets.append((part, before))
        before += n
    table = docs.sparkSession.createDataFrame(offsets, "_part string, _before long")
    number = F.floor((F.col("_before") + F.col("_place.at")) / F.lit(rows)).cast("long")
    return placed.join(F.broadcast(table), F.col("_place.part") == F.col("_part")).withColumn(name, number).drop("_place", "_part", "_before")


def op1_mixing(spark, sf_dir):
    return positions(load(spark, sf_dir, "documents", "doc_id", "source")).select("doc_id", "source", "block", "slot", "position")


QUERIES = {"op1_mixing": op1_mixing}
ORACLES: dict[str, str] = {}
