"""Shards of nearly equal bytes by a k-d tree over metadata.

A node that must hold several shards is split along its widest dimension, all
dimensions being scaled to 20 bits over the whole table, at the weighted median (for an
uneven number of shards, the matching quantile) of (value, hash of the id and checksum,
salt of the row). The cut is found by radix selection: four rounds of sums per node and
digit, which combine on the map side, so neither a hot value nor the root node gathers
rows anywhere. Equal values are cut apart by the hash and rows of the same id and text by
the salt, so sizes stay near equal whatever a group of copies holds: equal texts are not
kept in one shard, since one group of them can be larger than a shard.

Only DataFrame functions are used; rows with their texts are read once, for their sizes
and checksums, and afterwards only metadata moves.

Defined results: a null text has no bytes, and size 1; null ids, languages and sources
take part with fixed codes; repeated ids and rows each get a slot, and which of equal rows
goes where follows the split of the input; an empty table gives an empty
result; further columns are ignored.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from strata.llm.common import materialize

TOP = (1 << 20) - 1
#: Bits of a row's hash and of its salt, and of the digits of a key: the value, the hash and the salt.
HASH_BITS, SALT_BITS = 16, 14
DIGITS = (13, 13, 12, 12)
DIMENSIONS = ("size", "id", "lang", "source")


def _code(column):
    """A number from a text's md5, alike in every run."""
    return F.conv(F.substring(F.md5(F.coalesce(column.cast("string"), F.lit("null")).cast("binary")), 1, 5), 16, 10).cast("long")


def described(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """(id, size, text_crc32, h, lang, source): what the tree needs, without the text. h is the hash and the salt."""
    crc = F.crc32(F.coalesce(F.col(text_column), F.lit("")).cast("binary"))
    mixed = F.shiftright(_code(F.concat_ws(" ", F.coalesce(F.col(id_column).cast("string"), F.lit("null")), crc.cast("string"))), 20 - HASH_BITS)
    salt = F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(1 << SALT_BITS))
    return docs.select(
        F.col(id_column).alias("id"),
        (F.coalesce(F.octet_length(text_column), F.lit(0)).cast("long") + 1).alias("size"),
        crc.alias("text_crc32"),
        (mixed * (1 << SALT_BITS) + salt).alias("h"),
        _code(F.col("lang")).alias("lang"),
        _code(F.col("source")).alias("source"),
    )


def _scaled(light: DataFrame) -> DataFrame:
    """With q_<dimension>, in 0..2^20-1 over the range in the whole table."""
    number = {d: F.coalesce(F.col(d).cast("double"), F.lit(0.0)) for d in DIMENSIONS}
    ends = light.agg(*(f(number[d]).alias(f"{n}_{d}") for d in DIMENSIONS for n, f in (("min", F.min), ("max", F.max)))).first()
    out = light
    for d in DIMENSIONS:
        low, high = ends[f"min_{d}"], ends[f"max_{d}"]
        q = F.floor((number[d] - low) * TOP / (high - low)) if low is not None and high > low else F.lit(0)
        out = out.withColumn(f"q_{d}", q.cast("long"))
    return out


def _cuts(rows: DataFrame, dimensions: Sequence[str]) -> DataFrame:
    """(node, axis, cut): rows of a node with keys up to `cut` go left. `rows` have node, lo, hi (its shards)."""
    nodes = rows.groupBy("node", "lo", "hi").agg(F.sum("size").alias("weight"), *(F.max(f"q_{d}").alias(f"max_{d}") for d in dimensions), *(F.min(f"q_{d}").alias(f"min_{d}") for d in dimensions))
    widths = [F.struct((F.col(f"max_{d}") - F.col(f"min_{d}")).alias("width"), F.lit(-k).alias("k")) for k, d in enumerate(dimensions)]
    axis = -(F.array_max(F.array(*widths))["k"])
    left = F.floor((F.col("hi") - F.col("lo")) / 2)
    nodes = nodes.select("node", axis.alias("axis"), (F.col("weight") * left / (F.col("hi") - F.col("lo"))).alias("wanted"), F.lit(0).cast("long").alias("prefix"), F.lit(0).cast("long").alias("before"))
    nodes = materialize(nodes)
    done = 0
    for bits in DIGITS:
        done += bits
        # one row per node, of which there are no more than shards
        own = rows.join(F.broadcast(nodes), "node").withColumn("key", keyed(dimensions)).filter(F.shiftrightunsigned("key", sum(DIGITS) - done + bits) == F.col("prefix"))
        sums = own.groupBy("node", "wanted", "before", "prefix", F.col("axis"), F.shiftrightunsigned("key", sum(DIGITS) - done).alias("digit")).agg(F.sum("size").alias("weight"))
        upto = F.col("before") + F.sum("weight").over(Window.partitionBy("node").orderBy("digit"))
        reached = sums.withColumn("upto", upto).filter(F.col("upto") >= F.col("wanted"))
        nodes = materialize(reached.groupBy("node", "wanted", "axis").agg(F.min(F.struct("digit", "upto", "weight")).alias("x")).select("node", "wanted", "axis", F.col("x.digit").alias("prefix"), (F.col("x.upto") - F.col("x.weight")).alias("before"), F.col("x.upto").alias("upto")))
    # the last key goes right where that comes nearer to what is wanted
    nearer = (F.col("upto") - F.col("wanted") > F.col("wanted") - F.col("before")) & (F.col("before") > 0)
    return nodes.select("node", "axis", (F.col("prefix") - F.when(nearer, 1).otherwise(0)).alias("cut"))


def keyed(dimensions: Sequence[str]):
    value = F.coalesce(*(F.when(F.col("axis") == k, F.col(f"q_{d}")) for k, d in enumerate(dimensions)))
    return value * (1 << HASH_BITS + SALT_BITS) + F.col("h")


def assign(light: DataFrame, shards: int, dimensions: Sequence[str] = DIMENSIONS) -> DataFrame:
    """The rows of `described` with the shard they belong to."""
    rows = _scaled(light).withColumns({"node": F.lit(1).cast("long"), "lo": F.lit(0), "hi": F.lit(shards)})
    for _ in range((shards - 1).bit_length()):
        wide = rows.filter("hi - lo > 1")
        cuts = materialize(_cuts(wide, dimensions))
        rows = rows.join(F.broadcast(cuts), "node", "left").withColumn("key", keyed(dimensions))
        middle = F.col("lo") + F.floor((F.col("hi") - F.col("lo")) / 2).cast("int")
        side = F.when(F.col("key") > F.col("cut"), 1).otherwise(0)
        split = F.col("cut").isNotNull()
        rows = rows.select(*light.columns, *(f"q_{d}" for d in dimensions), F.when(split, F.col("node") * 2 + side).otherwise(F.col("node")).alias("node"), F.when(split & (side == 1), middle).otherwise(F.col("lo")).alias("lo"), F.when(split & (side == 0), middle).otherwise(F.col("hi")).alias("hi"))
        rows = materialize(rows)
    return rows.select(*light.columns, F.col("lo").alias("shard"))


def with_slots(rows: DataFrame, order: Sequence[str] = ("id", "text_crc32", "size", "h")) -> DataFrame:
    """With `slot`, gapless from 0 in each shard: rows are numbered in 4096 parts by salt, which offsets then join."""
    parted = rows.withColumn("part", F.pmod("h", F.lit(4096)))
    sizes = parted.groupBy("shard", "part").agg(F.count("*").alias("n"))
    offsets = sizes.select("shard", "part", (F.sum("n").over(Window.partitionBy("shard").orderBy("part")) - F.col("n")).alias("offset"))
    number = F.row_number().over(Window.partitionBy("shard", "part").orderBy(*order)) - 1
    return parted.withColumn("number", number).join(offsets, ["shard", "part"]).withColumn("slot", (F.col("offset") + F.col("number")).cast("long")).drop("part", "offset", "number")


def shard(docs: DataFrame, shards: int | None = None, target_bytes: int | None = None, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """One row per document: id, size, text_crc32, shard and slot. `target_bytes` sets the number of shards by the whole size."""
    light = materialize(described(docs, id_column, text_column))
    if shards is None:
        total = light.agg(F.sum("size")).first()[0] or 0
        shards = max(1, -(-total // int(target_bytes)))
    return with_slots(assign(light, shards)).select(F.col("id").alias(id_column), "size", "text_crc32", "shard", "slot")
