"""K-d tree sharding: weighted-median splits along the widest metadata dimension, in DataFrame operations only.

The tree is built over units: all rows with one text are a unit (of their summed weight and their least metadata), so a group
of copies shares a shard; only a group larger than a shard is cut into pieces.  Every unit gets, for each dimension, one 63-bit
key: 20 bits of its normalised position and 43 bits of a hash of the unit, which order the units of a node totally (up to hash
collisions), so a split is one threshold on one key.  Thresholds are found by distributed radix selection: a round sums the
weights of every node of a level by the next 11 bits of the key and sends at most ``nodes x 2048`` sums to the driver, whatever
the rows.  Large units, of which there are few, are set on a side first, in the order of their keys but for some beside the threshold, and
the threshold of the others makes up for them; so sizes stay near equal though groups stay whole.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Stored, gapless, join_skewed, row_uid, unsigned_crc32, utf8_bytes

POSITION_BITS, UNIT_BITS = 20, 43
KEY_BITS = POSITION_BITS + UNIT_BITS
DIGIT_BITS = 11
#: A split is refined until the bin it falls into holds at most this part of the node's weight.
TOLERANCE = 2.0**-14
#: A unit of more than one LARGEth of a shard is large; there are at most LARGE x shards of them.
LARGE = 64
#: Large units on each side of a threshold that may change sides.
NEAR = 16
#: Distinct strings that one task may rank.
RANKED_AT_ONCE = 10_000


@dataclass
class Cell:
    """An open node of the tree: how many shards it will hold, from which number on, and where it is split."""

    leaves: int
    first: int
    dim: int = 0
    threshold: int = 0

    def parts(self) -> tuple[Cell, Cell]:
        half = self.leaves // 2
        return Cell(half, self.first), Cell(self.leaves - half, self.first + half)


def _pick(values: list[int], index: Column) -> Column:
    """values[index] for an index column: one literal array, however many cells a level has."""
    return F.element_at(F.array(*[F.lit(v).cast("long") for v in values]), index.cast("int") + 1)


def ranks(values: DataFrame, name: str, store: Stored) -> tuple[DataFrame, int]:
    """(name, rank) of the distinct strings of a column, from 0 in their order, and how many there are: by one task if they
    are few, else by range partitions with carried-over counts."""
    found = store.put(values.select(name).where(F.col(name).isNotNull()).distinct())
    n = found.count()
    if n <= RANKED_AT_ONCE:
        return found.withColumn("_rank", F.row_number().over(Window.orderBy(name)) - 1), n
    laid = store.put(found.repartitionByRange(-(-n // RANKED_AT_ONCE), name).withColumn("_pid", F.spark_partition_id()))
    before = Window.orderBy("_pid").rowsBetween(Window.unboundedPreceding, -1)  # one row for each partition
    offsets = laid.groupBy("_pid").agg(F.count(F.lit(1)).alias("_n")).select("_pid", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_off"))
    inside = F.row_number().over(Window.partitionBy("_pid").orderBy(name))
    return laid.withColumn("_r", inside).join(offsets, "_pid").select(name, (F.col("_off") + F.col("_r") - 1).alias("_rank")), n


def _select(rows: DataFrame, cells: list[Cell], total: dict[int, int], goal: dict[int, float]) -> None:
    """Radix selection at once in every cell of ``total``; sets the ``threshold`` below which the weight is nearest to the
    cell's goal.

    rows: a stored table (_cell, _key, _w).  All open cells have fixed the same number of leading bits.
    """
    prefix, below = [0] * len(cells), [0] * len(cells)
    want = [goal.get(i, 0.0) for i in range(len(cells))]
    open_, bits = {i for i in total if total[i]}, 0
    while open_:
        shift = max(0, KEY_BITS - bits - DIGIT_BITS)
        mine = _pick([p if i in open_ else -1 for i, p in enumerate(prefix)], F.col("_cell"))
        sums = rows.where(F.shiftright("_key", KEY_BITS - bits) == mine if bits else mine == 0).groupBy("_cell", F.shiftright("_key", shift).alias("_d")).agg(F.sum("_w").alias("w"), F.count(F.lit(1)).alias("n")).collect()  # at most cells x 2048 rows
        found: dict[int, list] = {i: [] for i in open_}
        for r in sums:
            found[r["_cell"]].append((r["_d"], r["w"], r["n"]))
        for i in list(open_):
            for d, w, n in sorted(found[i]):
                if below[i] + w >= want[i]:
                    break
                below[i] += w
            prefix[i] = d
            if n == 1 or w <= TOLERANCE * total[i] or not shift:
                after = below[i] + w - want[i] < want[i] - below[i]  # the nearer side of the bin
                cells[i].threshold = min((d + after) << shift, 2**63 - 1)
                open_.discard(i)
        bits = KEY_BITS - shift


def _set_large(cells: list[Cell], large: dict[int, list[tuple[int, int, str]]], total: dict[int, int], goal: dict[int, float]) -> tuple[list[str], dict[int, int], dict[int, float]]:
    """Large units (key, weight, name) below a cell's threshold go to its low side.  Where the others cannot make up for
    them, units beside the threshold are moved over it or swapped, as long as that brings the sides nearer to the goal.
    Returns the names on low sides, the weight of the others in these cells, and their goals."""
    low_names, rest, left = [], {}, {}
    for i, units in large.items():
        units.sort()
        others = total[i] - sum(w for _, w, _ in units)
        n = sum(key < cells[i].threshold for key, _, _ in units)
        below, above = units[:n], units[n:]
        off = lambda low: max(low - goal[i], goal[i] - low - others, 0.0)
        low = sum(w for _, w, _ in below)
        while off(low) > 0:
            near = [None, *below[-NEAR:][::-1]], [None, *above[:NEAR]]
            moves = [(off(low - (x[1] if x else 0) + (y[1] if y else 0)), k + m, x, y) for k, x in enumerate(near[0]) for m, y in enumerate(near[1])]
            best = min(moves, key=lambda m: m[:2])
            if best[0] >= off(low):
                break
            _, _, x, y = best
            if x:
                below.remove(x)
                above.append(x)
            if y:
                above.remove(y)
                below.append(y)
            below.sort()
            above.sort()
            low = sum(w for _, w, _ in below)
        low_names += [u for _, _, u in below]
        left[i] = min(max(goal[i] - low, 0.0), float(others))
        if others:
            rest[i] = others
        cells[i].threshold = 0
    return low_names, rest, left


def _units(raw: DataFrame, names: list[str], shards: int, store: Stored) -> tuple[DataFrame, DataFrame, float]:
    """Stored rows with their unit ``_u``, stored units (_u, _w, _n rows, positions), and the mean weight of a shard."""
    least = F.min(F.struct(*[f"{n}v" for n in names])).alias("_at")
    groups = store.put(raw.groupBy("_g").agg(F.sum("_w").alias("_w"), F.count(F.lit(1)).alias("_n"), least))
    mean = (groups.agg(F.sum("_w")).first()[0] or 0) / shards
    over = groups.where((F.col("_w") > mean) & (F.col("_n") > 1)).select("_g", "_w").collect() if mean else []  # fewer than shards
    flat = lambda df: df.select("_u", "_w", "_n", *[F.col(f"_at.{n}v").alias(f"{n}v") for n in names])
    if not over:
        return raw.withColumnRenamed("_g", "_u"), store.put(flat(groups.withColumnRenamed("_g", "_u"))), mean
    pieces = F.element_at(F.create_map(*[F.lit(x) for r in over for x in (r["_g"], -(-r["_w"] * LARGE // max(1, int(mean))))]), F.col("_g"))
    cut = store.put(raw.withColumn("_u", F.when(pieces.isNull(), F.col("_g")).otherwise(F.concat_ws(":", "_g", F.pmod(F.xxhash64("_uid"), pieces).cast("string")))).drop("_g"))
    some = F.col("_g").isin([r["_g"] for r in over])
    parts = cut.where(F.split("_u", ":")[0].isin([r["_g"] for r in over])).groupBy("_u").agg(F.sum("_w").alias("_w"), F.count(F.lit(1)).alias("_n"), least)
    return cut, store.put(flat(groups.where(~some).withColumnRenamed("_g", "_u")).unionByName(flat(parts))), mean


def kd_tree_shards(df: DataFrame, dims: dict[str, Column], weight: Column, shards: int, text: Column, shard: str = "shard", keep: dict[str, Column] | None = None, slot: str = "slot") -> DataFrame:
    """Split ``df`` into ``shards`` leaves of near equal weight and number the rows of each leaf from 0.

    df: any table; only ``keep`` (name to expression), the shard and the slot are returned, so extra columns of ``df``
    never clash.  dims: numeric expressions, or strings, which are placed by their ranks; a null takes the least position.
    weight: non-negative long, null counts 0.  text: rows with an equal one share a shard, unless they weigh more than a shard;
    null is equal to nothing.  A node with k leaves splits k//2 : k - k//2 by weight, along the dimension with the widest
    normalised range inside the node.  Empty table: empty result.  Repeated rows are rows of one group.
    """
    store = Stored(df.sparkSession)
    names = [f"_k{i}" for i in range(len(dims))]
    keep = keep or {}
    strings = [n for n, e in zip(names, dims.values()) if df.select(e.alias("x")).dtypes[0][1] == "string"]
    raw = store.put(df.select(*[e.alias(k) for k, e in keep.items()], *[e.alias(f"{n}v") for n, e in zip(names, dims.values())], F.coalesce(weight, F.lit(0)).cast("long").alias("_w"), row_uid().alias("_uid"), F.md5(text.cast("string")).alias("_g")))
    rows_ = raw.count()
    raw = raw.withColumn("_g", F.coalesce("_g", F.concat(F.lit("row"), F.col("_uid").cast("string"))))
    raw, units, mean = _units(raw, names, shards, store)
    for n in strings:
        values, found = ranks(units, f"{n}v", store)
        values = F.broadcast(values) if found <= RANKED_AT_ONCE else values
        units = units.join(values, f"{n}v", "left").withColumn(f"{n}v", F.col("_rank")).drop("_rank")
    units = store.put(units)
    ends = units.agg(*[f(f"{n}v").alias(f"{g}{n}") for n in names for g, f in (("lo", F.min), ("hi", F.max))]).first()
    keys = []
    for n in names:
        lo, hi = ends[f"lo{n}"], ends[f"hi{n}"]
        span = (hi - lo) if lo is not None and hi > lo else None
        at = F.least(F.floor((F.col(f"{n}v") - F.lit(lo)) / F.lit(span) * F.lit(2.0**POSITION_BITS)), F.lit(2**POSITION_BITS - 1)) if span else F.lit(0)
        keys.append((F.shiftleft(F.coalesce(at, F.lit(0)).cast("long"), UNIT_BITS) + F.shiftrightunsigned(F.xxhash64("_u"), 64 - UNIT_BITS)).alias(n))
    tree = store.put(units.select("_u", "_w", "_n", (F.col("_w") * LARGE > mean).alias("_large"), F.lit(0).cast("long").alias("_cell"), *keys))
    store.drop(units)
    cells = [Cell(shards, 0)]
    while any(c.leaves > 1 for c in cells):
        top = lambda n, f: f(F.shiftright(n, UNIT_BITS))
        seen = tree.groupBy("_cell").agg(F.sum("_w").alias("w"), *[(top(n, F.max) - top(n, F.min)).alias(n) for n in names]).collect()  # at most one row for each shard
        for r in seen:
            cells[r["_cell"]].dim = max(range(len(names)), key=lambda k: r[names[k]])
        total = {r["_cell"]: r["w"] for r in seen if cells[r["_cell"]].leaves > 1}
        goal = {i: w * (cells[i].leaves // 2) / cells[i].leaves for i, w in total.items()}
        key = F.element_at(F.array(*names), _pick([c.dim for c in cells], F.col("_cell")).cast("int") + 1)
        keyed = store.put(tree.select("_u", "_cell", "_w", "_large", key.alias("_key")))
        _select(keyed, cells, total, goal)
        large: dict[int, list[tuple[int, int, str]]] = {}
        for r in keyed.where("_large").collect():  # at most LARGE x shards units
            if r["_cell"] in total:
                large.setdefault(r["_cell"], []).append((r["_key"], r["_w"], r["_u"]))
        low_names, rest, left = _set_large(cells, large, total, goal)
        if rest:
            _select(keyed.where(~F.col("_large")), cells, rest, left)
        store.drop(keyed)
        after, low, high = [], [], []
        for c in cells:
            low.append(len(after))
            after += c.parts() if c.leaves > 1 else [c]
            high.append(len(after) - 1)
        below = F.when(F.col("_large"), F.col("_u").isin(low_names)).otherwise(key < _pick([c.threshold for c in cells], F.col("_cell")))
        moved = store.put(tree.withColumn("_cell", F.when(below, _pick(low, F.col("_cell"))).otherwise(_pick(high, F.col("_cell")))))
        store.drop(tree)
        tree, cells = moved, after
    homes = tree.select("_u", "_n", _pick([c.first for c in cells], F.col("_cell")).cast("int").alias(shard))
    placed = store.put(join_skewed(raw.select(*keep, "_uid", "_u"), homes, ["_u"], "_n", rows_).drop("_u"))
    return gapless(placed, [shard], "_uid", slot, rows_).drop("_uid")


def shard_documents(docs: DataFrame, shards: int = 40) -> DataFrame:
    """The sharding contract for ``documents``: law ``bytes``; equal texts are a group.

    Null text: no bytes, so size 16 and the CRC of nothing.  Null metadata: least position of its dimension.
    """
    size = utf8_bytes(F.col("text")) + 16
    dims = {
        "source": F.col("source").cast("string"),
        "lang": F.col("lang").cast("string"),
        "length": F.log2(size.cast("double")),
        "doc_id": F.col("doc_id").cast("double"),
    }
    keep = {"doc_id": F.col("doc_id"), "size": size, "text_crc32": unsigned_crc32(F.col("text"))}
    out = kd_tree_shards(docs, dims, size, shards, F.col("text"), keep=keep)
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
