"""Sharding by a Hilbert curve over quantised metadata; DataFrame functions only.

Each metadata dimension is quantised into equally filled cells (edges from approximate
percentiles over all rows), the cells are mapped to a Hilbert index, and the sorted
rows are cut into runs. Near rows in any dimension then share few shards, so a
shard's minima and maxima prune well in every dimension at once.

Defined results: null metadata and unknown kinds go to cell 0; a null text counts as
an empty one; equal texts are neighbours on the curve (the row with the least id
supplies the group's place) and stay in one shard unless the group is larger than
``1/whole_part`` of a shard; rows that repeat are placed one by one; an empty table
gives an empty result; columns beside those named are ignored.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.ordering import running_totals


def _rotate_left(x: Column, by: Column, n: int) -> Column:
    return ((F.call_function("shiftleft", x, by)).bitwiseOR(F.call_function("shiftright", x, F.lit(n) - by))).bitwiseAND(F.lit((1 << n) - 1))


def _tables(n: int) -> tuple[list[int], list[int], list[int]]:
    """By sub-cell number: inverse Gray code, entry corner and direction of the curve."""
    size = 1 << n
    inverse = [0] * size
    for i in range(size):
        inverse[i ^ (i >> 1)] = i
    trailing = [((~i & (i + 1)).bit_length() - 1) for i in range(size)]
    entry = [0 if i == 0 else ((j := 2 * ((i - 1) // 2)) ^ (j >> 1)) for i in range(size)]
    turn = [0 if i == 0 else (trailing[i - 1] if i % 2 == 0 else trailing[i]) % n for i in range(size)]
    return inverse, entry, turn


def hilbert_index(cells: list[Column], bits: int) -> Column:
    """The Hilbert index (a long) of a cell given by one ``bits``-wide int for each dimension.

    The walk from the top bit down is one ``aggregate`` whose state is the index so
    far, the entry corner and the direction of the current sub-cube.
    """
    n = len(cells)
    if n < 2 or n > 6 or n * bits > 62:
        raise ValueError("2 to 6 dimensions of at most 62 bits together")
    inverse, entry, turn = (F.array(*[F.lit(x) for x in t]) for t in _tables(n))
    whole = F.array(*[c.cast("int") for c in cells])

    def step(state: Column, bit: Column) -> Column:
        corner, way = state["e"], state["d"]
        label = reduce(
            lambda a, b: a.bitwiseOR(b),
            [F.shiftleft(F.call_function("shiftright", F.get(whole, F.lit(i)), bit).bitwiseAND(F.lit(1)), i) for i in range(n)],
        )
        back = _rotate_left(label.bitwiseXOR(corner), (F.lit(2 * n) - way - F.lit(1)) % F.lit(n), n)
        w = F.get(inverse, back)
        return F.struct(
            (F.shiftleft(state["h"], n).bitwiseOR(w.cast("long"))).alias("h"),
            corner.bitwiseXOR(_rotate_left(F.get(entry, w), (way + F.lit(1)) % F.lit(n), n)).alias("e"),
            ((way + F.get(turn, w) + F.lit(1)) % F.lit(n)).cast("int").alias("d"),
        )

    start = F.struct(F.lit(0).cast("long").alias("h"), F.lit(0).alias("e"), F.lit(0).alias("d"))
    return F.aggregate(F.sequence(F.lit(bits - 1), F.lit(0), F.lit(-1)), start, step, lambda s: s["h"])


def _as_number(df: DataFrame, name: str) -> Column:
    """Numbers as they are; strings by their first seven bytes, which keeps their order."""
    kind = dict(df.dtypes)[name]
    if kind == "string":
        return F.conv(F.rpad(F.substring(F.hex(F.encode(F.col(name), "UTF-8")), 1, 14), 14, "0"), 16, 10).cast("double")
    if kind in ("timestamp", "date", "timestamp_ntz"):
        return F.unix_timestamp(F.col(name).cast("timestamp")).cast("double")
    return F.col(name).cast("double")


def cell_edges(df: DataFrame, dims: list[str], bits: int) -> dict[str, list[float]]:
    """At most ``2**bits - 1`` inner edges for each dimension, from percentiles over all rows."""
    cells = 1 << bits
    asked = F.array(*[F.lit(i / cells) for i in range(1, cells)])
    row = df.select(*[_as_number(df, d).alias(f"_{i}") for i, d in enumerate(dims)]).agg(*[F.percentile_approx(f"_{i}", asked, F.lit(2000)).alias(f"_{i}") for i in range(len(dims))]).first()
    return {d: sorted(set(row[i] or [])) for i, d in enumerate(dims)}


def cell(df: DataFrame, dim: str, edges: list[float]) -> Column:
    """Number of edges at or below the value; 0 for null."""
    value = _as_number(df, dim)
    if not edges:
        return F.lit(0)
    return F.coalesce(F.size(F.filter(F.array(*[F.lit(float(e)) for e in edges]), lambda e: e <= value)), F.lit(0)) * F.when(value.isNull(), 0).otherwise(1)


def shard_documents(df: DataFrame, shards: int, dims: list[str], bits: int = 5, law: str = "bytes", id_col: str = "doc_id", text_col: str = "text", whole_part: int = 16) -> DataFrame:
    """Place every row: ``(id, size, text_crc32, hilbert, shard, slot, <dims>)``.

    ``law='bytes'`` cuts runs of nearly equal bytes; ``law='rows'`` cuts runs whose row
    counts differ by one at most (groups are then cut where the counts ask for it).
    """
    if law not in ("bytes", "rows"):
        raise ValueError("law is bytes or rows")
    edges = cell_edges(df, dims, bits)
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = df.select(
        F.col(id_col).alias("_id"),
        (F.octet_length(text).cast("long") + 8).alias("_size"),
        F.crc32(F.encode(text, "UTF-8")).alias("_crc"),
        F.xxhash64(text).alias("_key"),
        F.struct(*[cell(df, d, edges[d]).cast("int").alias(f"c{i}") for i, d in enumerate(dims)]).alias("_cells"),
        *[F.col(d).alias(f"_dim{i}") for i, d in enumerate(dims)],
    )
    key = ["_key", "_crc", "_size"]
    groups = rows.groupBy(*key).agg(F.min(F.struct("_id", "_cells")).alias("_first"), F.sum("_size").alias("_group"), F.count("*").alias("_n"))
    groups = groups.select(*key, "_group", "_n", hilbert_index([F.col("_first._cells")[f"c{i}"] for i in range(len(dims))], bits).alias("_h"))
    groups = running_totals(groups, ["_h", *key], {"_start": "_group"}, label="groups")
    placed = rows.drop("_cells").join(groups, key)
    placed = placed.withColumn("_one", F.lit(1).cast("long"))
    placed = running_totals(placed, ["_h", *key, "_id"], {"_before": "_size", "_rank": "_one"}, label="rows")
    total, count = placed.agg(F.coalesce(F.sum("_size"), F.lit(0)), F.count("*")).first()
    if law == "bytes":
        whole = F.col("_group") * F.lit(whole_part * shards) <= F.lit(total)
        middle = F.when(whole, F.col("_start") * 2 + F.col("_group")).otherwise(F.col("_before") * 2 + F.col("_size"))
        shard = F.call_function("div", middle * shards, F.lit(max(2 * total, 1)))
    else:
        shard = F.call_function("div", F.col("_rank") * shards, F.lit(max(count, 1)))
    placed = placed.withColumn("_shard", F.least(shard.cast("int"), F.lit(shards - 1)))
    first = placed.groupBy("_shard").agg(F.min("_rank").alias("_first_rank"))  # one row a shard
    return placed.join(F.broadcast(first), "_shard").select(
        F.col("_id").alias(id_col),
        F.col("_size").alias("size"),
        F.col("_crc").alias("text_crc32"),
        F.col("_h").alias("hilbert"),
        F.col("_shard").alias("shard"),
        (F.col("_rank") - F.col("_first_rank")).alias("slot"),
        *[F.col(f"_dim{i}").alias(d if d not in (id_col, "size", "text_crc32", "hilbert", "shard", "slot") else f"dim_{d}") for i, d in enumerate(dims)],
    )


def manifest(placed: DataFrame, dims: list[str]) -> DataFrame:
    """One row a shard with rows, bytes and each dimension's least and largest value."""
    return placed.groupBy("shard").agg(F.count("*").alias("rows"), F.sum("size").alias("bytes"), *[f(d).alias(f"{n}_{d}") for d in dims for n, f in (("min", F.min), ("max", F.max))])


def matching_shards(listed: DataFrame, **ranges: tuple) -> DataFrame:
    """Shards of a manifest that may hold rows with every dimension in its (low, high)."""
    for dim, (low, high) in ranges.items():
        listed = listed.where((F.col(f"max_{dim}") >= F.lit(low)) & (F.col(f"min_{dim}") <= F.lit(high)))
    return listed.select("shard")


def write_shards(placed: DataFrame, rows: DataFrame, path: str, id_col: str = "doc_id") -> None:
    """Write the rows below ``shard=N`` folders, each in slot order.

    A shard is dealt to several tasks by its slots, so a large one is no single task.
    """
    joined = rows.join(placed.select(id_col, "shard", "slot"), id_col)
    joined.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
