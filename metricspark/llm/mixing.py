"""Mixing sources to target weights by Pfair scheduling, in DataFrame operations alone.

A source of weight w gets blocks of documents. Its i-th block (from 0) is released at slot floor(i / w) and due at
ceil((i + 1) / w). Each slot goes to the released block with the earliest deadline (ties: first source). With
weights that sum to 1, every source has at all times received its share up to less than one block.

Weights are whole units u of W = sum(u), so the schedule repeats every W slots: one period is planned on the
driver (at most MOST_SLOTS rows, checked) and block b of a source sits at (b div u) * W + slot(b mod u). The documents
are numbered in levels, so that no source, however large, meets in one task: each source is cut into buckets by a hash
prefix of the doc_id, buckets are counted and summed up in two levels, and rows are numbered within buckets. A bucket
far over its expected size holds a doc_id that repeats; it is cut again by a hash of the whole row and the row's number.
When a source has no more blocks its slots stay empty; the others keep their order and ratios. No row is dropped or repeated.

A null source is a source of its own. Rows are ordered by the hash of the doc_id, the doc_id (null first) and a hash of
the row, so ties are rows equal in all columns, which are alike. Texts, null, empty or long, are only carried along. An empty
table gives an empty result. Extra columns pass through; `mix_positions` replaces those that are named like a column it adds, `mixed` keeps all.
"""
from __future__ import annotations

import heapq
import json

from pyspark.sql import DataFrame, Window, functions as F

from .common import written

UNITS = 100
BLOCK_ROWS = 64
BUCKET_ROWS = 1000
CROWDED = 8  # a bucket of that many times BUCKET_ROWS holds a repeated doc_id
MOST_SLOTS = 200_000  # of one period: the bound of what the driver plans and tasks get by broadcast
MOST_CROWDED = 100_000  # buckets that are broadcast; more are joined
ADDED = ["block", "slot", "release", "deadline", "place"]
SEED = "mix"


def period(units: list[int]) -> list[tuple[int, int, int]]:
    """(source, i, slot) of every block of one period, planned by earliest deadline first among released blocks."""
    whole = sum(units)
    waiting = [(0, s, 0) for s, u in enumerate(units) if u > 0]  # release, source, i
    heapq.heapify(waiting)
    ready: list[tuple[int, int, int]] = []
    out = []
    for slot in range(whole):
        while waiting and waiting[0][0] <= slot:
            _, s, i = heapq.heappop(waiting)
            heapq.heappush(ready, (-(-(i + 1) * whole // units[s]), s, i))
        _, s, i = heapq.heappop(ready)
        out.append((s, i, slot))
        if i + 1 < units[s]:
            heapq.heappush(waiting, ((i + 1) * whole // units[s], s, i + 1))
    return out


def tempered_units(counts: dict[str | None, int], temperature: float = 2.0, units: int = UNITS) -> dict[str | None, int]:
    """Target weights as whole units: the largest source gets `units`, others by count ** (1 / temperature)."""
    top = max(counts.values(), default=1)
    return {s: max(1, int(units * (n / top) ** (1 / temperature) + 0.5)) for s, n in counts.items()}


def _key(source: str | None) -> str:
    """Sources by a key that is never null, so that numbering and joins share one partitioning."""
    return "" if source is None else f"={source}"


def _source_counts(rows: DataFrame) -> dict[str | None, int]:
    found = rows.groupBy("s_").agg(F.count("*").alias("n")).limit(MOST_SLOTS + 1).collect()  # one row a source
    if len(found) > MOST_SLOTS:
        raise ValueError(f"more than {MOST_SLOTS} sources; give fewer, larger sources")
    return {r.s_[1:] if r.s_ else None: r.n for r in found}


def _units(counts: dict[str | None, int], weights: dict[str | None, int] | None) -> dict[str | None, int]:
    units = {s: weights.get(s, 1) for s in counts} if weights else tempered_units(counts)
    if any(u < 1 or u != int(u) for u in units.values()):
        raise ValueError("weights are whole numbers from 1 on")
    if sum(units.values()) > MOST_SLOTS:
        raise ValueError(f"a period of more than {MOST_SLOTS} slots; divide the weights")
    return units


def _cut_crowded(rows: DataFrame, sizes: DataFrame, bucket_rows: int) -> tuple[DataFrame, bool]:
    """`rows` with part_, 0 but in crowded buckets, which are cut by row hash and row number; and whether no bucket is."""
    crowded = sizes.where(F.col("n_") > CROWDED * bucket_rows).select(F.col("s_").alias("cs_"), F.col("k_").alias("ck_"), F.ceil(F.col("n_") / bucket_rows).alias("parts_"))
    n = crowded.count()
    if not n:
        return rows.withColumn("part_", F.lit(0).cast("long")), True
    crowded = F.broadcast(crowded) if n <= MOST_CROWDED else crowded
    lane = F.pmod(F.xxhash64("t_", F.monotonically_increasing_id()), F.coalesce("parts_", F.lit(1)))
    return rows.join(crowded, (F.col("s_") == F.col("cs_")) & (F.col("k_") == F.col("ck_")), "left").withColumn("part_", lane.cast("long")).drop("cs_", "ck_", "parts_"), False


def _rows_before(sizes: DataFrame, coarse: int) -> DataFrame:
    """[bs_, bk_, bp_, before_]: rows of the source in earlier buckets; summed within runs of buckets of a common prefix, and over the runs."""
    runs = sizes.withColumn("c_", F.substring("k_", 1, coarse))
    total = runs.groupBy(F.col("s_").alias("rs_"), F.col("c_").alias("rc_")).agg(F.sum("n_").alias("r_"))
    total = total.withColumn("earlier_", F.sum("r_").over(Window.partitionBy("rs_").orderBy("rc_")) - F.col("r_"))
    inside = runs.withColumn("in_", F.sum("n_").over(Window.partitionBy("s_", "c_").orderBy("k_", "part_")) - F.col("n_"))
    both = inside.join(total, (F.col("s_") == F.col("rs_")) & (F.col("c_") == F.col("rc_")))
    return both.select(F.col("s_").alias("bs_"), F.col("k_").alias("bk_"), F.col("part_").alias("bp_"), (F.col("earlier_") + F.col("in_")).alias("before_"))


def _placed(docs: DataFrame, weights: dict[str | None, int] | None, block_rows: int, bucket_rows: int) -> DataFrame:
    """[row_, block, slot, release, deadline, place]; row_ holds the whole row, so no column of it can clash."""
    spark = docs.sparkSession
    hashed = [f.name for f in docs.schema.fields if "map<" not in f.dataType.simpleString()]
    rows = docs.select(F.coalesce(F.concat(F.lit("="), F.col("source").cast("string")), F.lit("")).alias("s_"), F.col("doc_id").cast("long").alias("id_"), F.xxhash64(*hashed).alias("t_"), F.struct("*").alias("row_"))
    counts = _source_counts(rows)
    units = _units(counts, weights)
    names = sorted(counts, key=lambda s: (s is not None, s or ""))
    whole = sum(units.values())
    slots = _rows(spark, [{"ps_": _key(names[s]), "i_": i, "t0_": t} for s, i, t in period([units[s] for s in names])], "array<struct<ps_:string,i_:bigint,t0_:bigint>>")
    amounts = _rows(spark, [{"us_": _key(s), "u_": u} for s, u in units.items()], "array<struct<us_:string,u_:bigint>>")

    digits = 1
    while max(counts.values(), default=0) > bucket_rows * 16**digits:
        digits += 1
    h = F.md5(F.concat(F.lit(f"{SEED}:"), F.coalesce(F.col("id_").cast("string"), F.lit(""))))
    rows = rows.withColumn("h_", h).withColumn("k_", F.substring("h_", 1, digits))
    sizes = written(rows.groupBy("s_", "k_").agg(F.count("*").alias("n_")), "mix-buckets")
    cut, whole_buckets = _cut_crowded(rows, sizes, bucket_rows)
    fine = sizes.withColumn("part_", F.lit(0).cast("long")) if whole_buckets else cut.groupBy("s_", "k_", "part_").agg(F.count("*").alias("n_"))
    before = _rows_before(fine, digits // 2)
    before = F.broadcast(before) if whole_buckets and sizes.count() <= MOST_CROWDED else before
    order = Window.partitionBy("s_", "k_", "part_").orderBy("h_", "id_", "t_")
    numbered = cut.withColumn("r_", F.row_number().over(order) - 1)
    numbered = numbered.join(before, (F.col("s_") == F.col("bs_")) & (F.col("k_") == F.col("bk_")) & (F.col("part_") == F.col("bp_"))).withColumn("r_", F.col("r_") + F.col("before_"))
    numbered = numbered.withColumn("block", F.expr(f"r_ div {block_rows}")).withColumn("place", F.col("r_") % block_rows)
    with_units = numbered.join(F.broadcast(amounts), F.col("s_") == F.col("us_")).withColumn("b_", F.col("block") % F.col("u_"))
    out = with_units.join(F.broadcast(slots), (F.col("s_") == F.col("ps_")) & (F.col("b_") == F.col("i_")))
    out = out.withColumn("slot", F.expr(f"block div u_ * {whole} + t0_"))
    out = out.withColumn("release", F.expr(f"(block * {whole}) div u_")).withColumn("deadline", F.expr(f"((block + 1) * {whole} + u_ - 1) div u_"))
    return out.select("row_", *ADDED)


def mix_positions(docs: DataFrame, weights: dict[str | None, int] | None = None, block_rows: int = BLOCK_ROWS, bucket_rows: int = BUCKET_ROWS) -> DataFrame:
    """`docs` with block (in its source), slot, release, deadline, place (row in the block). (slot, place) is the mixed order.

    `weights` are whole units by source; without them the tempered counts are used. Sources missing in `weights` get one unit.
    """
    kept = [F.col("row_")[c].alias(c) for c in docs.columns if c not in ADDED]
    return _placed(docs, weights, block_rows, bucket_rows).select(*kept, *ADDED)


def _rows(spark, rows: list[dict], kind: str) -> DataFrame:
    return spark.range(1).select(F.explode(F.from_json(F.lit(json.dumps(rows)), kind)).alias("x")).select("x.*")


def mixed(docs: DataFrame, weights: dict[str | None, int] | None = None, block_rows: int = BLOCK_ROWS, bucket_rows: int = BUCKET_ROWS) -> DataFrame:
    """`docs`, its own columns, laid out in the mixed order: partitions by ranges of slots, sorted within."""
    at = _placed(docs, weights, block_rows, bucket_rows)
    return at.repartitionByRange("slot", "place").sortWithinPartitions("slot", "place").select("row_.*")
