"""Sharding by a hierarchical weighted hash tree, on DataFrame functions only.

Regions hold racks and racks hold shards. At each level a row draws one child: every child gets a uniform hash of
(row key, child name) and scores -ln(u) / weight, and the least score wins, so a child wins in proportion to its
weight. A change of one weight changes scores only there; a new branch takes rows only into itself.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from writelite.llm.common import bucket_count


@dataclass(frozen=True)
class Branch:
    """A region, rack or shard. weight counts for a leaf; another branch weighs as much as what hangs below it."""

    name: str
    weight: float = 1.0
    children: tuple[Branch, ...] = ()
    shard: int = -1

    @property
    def mass(self) -> float:
        return sum(c.mass for c in self.children) if self.children else self.weight


def default_tree(shards: int, racks_per_region: int = 2, shards_per_rack: int = 4, base: int = 16) -> Branch:
    """`base` shards in full racks; each further shard hangs as a region of its own, so that growth moves rows only into it.

    >>> [default_tree(17).children[-1].name, default_tree(16).mass]
    ['region-x16', 16.0]
    """
    leaf = lambda s: Branch(f"shard-{s}", shard=s)
    racks = [Branch(f"rack-{r}", children=tuple(leaf(s) for s in range(r * shards_per_rack, min((r + 1) * shards_per_rack, base, shards)))) for r in range(-(-min(base, shards) // shards_per_rack))]
    regions = [Branch(f"region-{g}", children=tuple(racks[g * racks_per_region : (g + 1) * racks_per_region])) for g in range(-(-len(racks) // racks_per_region))]
    extra = [Branch(f"region-x{s}", children=(Branch(f"rack-x{s}", children=(leaf(s),)),)) for s in range(base, shards)]
    return Branch("root", children=tuple(regions + extra))


def _uniform(key: Column, name: str) -> Column:
    """In (0, 1): 53 bits of a hash of the key and the name of the child."""
    return (F.shiftrightunsigned(F.xxhash64(key, F.lit(name)), 11).cast("double") + 0.5) / F.lit(float(2**53))


def place(key: Column, tree: Branch) -> Column:
    """The shard number that a key draws on its way down the tree."""
    if not tree.children:
        return F.lit(tree.shard)
    alive = [c for c in tree.children if c.mass > 0]
    if len(alive) == 1:
        return place(key, alive[0])
    draws = [F.struct((-F.log(_uniform(key, c.name)) / F.lit(float(c.mass))).alias("score"), F.lit(i).alias("i")) for i, c in enumerate(alive)]
    won = F.array_min(F.array(*draws)).getField("i")
    out = F.when(won == 0, place(key, alive[0]))
    for i, c in enumerate(alive[1:], 1):
        out = out.when(won == i, place(key, c))
    return out


def shard(df: DataFrame, key: str = "doc_id", text: str = "text", tree: Branch | None = None, grown: Branch | None = None) -> DataFrame:
    """Rows (doc_id, size, text_crc32, law, shard, slot, grown_shard).

    size is the UTF-8 bytes of the text plus 1 (a null text has none and crc32 0); law is always 'key': the key and the
    tree decide. A null key is a key like any other (it draws by the child names alone); repeated rows go to one shard
    and take a slot each; an empty table gives no rows; other columns are ignored. slot numbers a shard's rows from 0
    without gaps: rows are numbered inside hashed parts of each shard and parts are offset by the counts of those before.
    """
    tree, grown = tree or default_tree(16), grown or default_tree(17)
    spark = df.sparkSession
    text_, k = F.coalesce(F.col(text), F.lit("")), F.col(key)
    rows = df.select(
        k.alias("doc_id"),
        (F.octet_length(text_) + 1).cast("long").alias("size"),
        F.crc32(F.encode(text_, "UTF-8")).alias("text_crc32"),
        F.lit("key").alias("law"),
        place(k, tree).cast("int").alias("shard"),
        place(k, grown).cast("int").alias("grown_shard"),
    )
    # A part mixes in what else the row has, so that many rows of one key are spread too.
    n = df.count()
    parts = bucket_count(spark, n, 200_000)
    rows = rows.withColumn("part", F.pmod(F.xxhash64("doc_id", "size", "text_crc32"), F.lit(parts)).cast("int"))
    rows = rows.repartition(parts, "shard", "part")
    sizes = rows.groupBy("shard", "part").agg(F.count(F.lit(1)).alias("n"))
    from pyspark.sql import Window as W

    offsets = sizes.withColumn("before", F.sum("n").over(W.partitionBy("shard").orderBy("part").rowsBetween(W.unboundedPreceding, -1))).select("shard", "part", F.coalesce("before", F.lit(0)).alias("before"))
    inner = W.partitionBy("shard", "part").orderBy("doc_id", "size", "text_crc32")
    out = rows.withColumn("nth", F.row_number().over(inner)).join(offsets, ["shard", "part"])
    return out.select("doc_id", "size", "text_crc32", "law", "shard", (F.col("before") + F.col("nth") - 1).cast("long").alias("slot"), "grown_shard")
