"""Sharding by a hierarchical weighted hash tree: region, rack, shard.

At each level a document draws one number per child, -ln(u) / weight with u from a hash of its doc_id and the child's
name, and goes to the child with the smallest; a child so gets rows in proportion to its weight, which is the sum of the
weights below it. A change of weights moves rows only into or out of subtrees whose weights change. New shards come as a
branch of their own (a region with one rack with one shard), so a row either stays or goes to the new shard: law `key`.

Only column functions are used and no row needs another, but for the slots: ranges of (shard, doc_id) are numbered task by
task and shifted by the sums of the tasks before, so a shard of any size is spread over many tasks.

Defined cases: the size of a null text is that of no bytes, its crc32 that of the empty string; a null doc_id draws like
the hash seed alone and sorts last; rows that tie in doc_id are numbered by a hash of their texts; repeated rows land in
one shard with a slot each; very long texts are only measured; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkverdict.llm.common import ordered_positions

OVERHEAD = 16


@dataclass(frozen=True)
class Tree:
    """regions[i][j] = {shard: weight} of rack j of region i."""

    regions: tuple[tuple[tuple[tuple[int, float], ...], ...], ...]

    @staticmethod
    def regular(regions: int, racks: int, shards: int) -> Tree:
        number = iter(range(regions * racks * shards))
        return Tree(tuple(tuple(tuple((next(number), 1.0) for _ in range(shards)) for _ in range(racks)) for _ in range(regions)))

    def grown(self, weight: float = 1.0) -> Tree:
        """One more shard, on a branch of its own."""
        new = 1 + max(s for region in self.regions for rack in region for s, _ in rack)
        return Tree((*self.regions, (((new, weight),),)))


def _draw(key: Column, level: str, children: list[tuple[str, float]]) -> Column:
    """Index of the child with the smallest weighted draw; the name orders ties."""
    draws = []
    for i, (name, weight) in enumerate(children):
        # the upper 53 bits, moved off zero, as a number in (0, 1)
        u = (F.shiftrightunsigned(F.xxhash64(key, F.lit(level), F.lit(name)), 11).cast("double") + 0.5) / float(1 << 53)
        draws.append(F.struct((-F.log(u) / weight).alias("d"), F.lit(i).alias("i")))
    return F.array_min(F.array(*draws))["i"] if len(draws) > 1 else F.lit(0)


def _choose(index: Column, options: list[Column]) -> Column:
    return F.element_at(F.array(*options), index + 1) if len(options) > 1 else options[0]


def _case(index: Column, branches: list[Column]) -> Column:
    """Only the branch that is taken is computed."""
    out = branches[-1]
    for i in reversed(range(len(branches) - 1)):
        out = F.when(index == i, branches[i]).otherwise(out)
    return out


def assign(df: DataFrame, tree: Tree, key: str, out: str) -> DataFrame:
    """Adds the shard of each row."""
    k = F.col(key)
    weigh = lambda rack: sum(w for _, w in rack)
    region = _draw(k, "region", [(str(i), sum(map(weigh, racks))) for i, racks in enumerate(tree.regions)])
    df = df.withColumn("_region", region)
    df = df.withColumn("_rack", _case(F.col("_region"), [_draw(k, f"rack/{i}", [(str(j), weigh(rack)) for j, rack in enumerate(racks)]) for i, racks in enumerate(tree.regions)]))
    places, index = [], []
    for i, racks in enumerate(tree.regions):
        for j, rack in enumerate(racks):
            index.append((i, j))
            places.append(_choose(_draw(k, f"shard/{i}/{j}", [(str(s), w) for s, w in rack]), [F.lit(s) for s, _ in rack]))
    chosen = places[-1]
    for (i, j), place in reversed(list(zip(index[:-1], places[:-1], strict=True))):
        chosen = F.when((F.col("_region") == i) & (F.col("_rack") == j), place).otherwise(chosen)
    return df.withColumn(out, chosen.cast("int")).drop("_region", "_rack")


def shard(docs: DataFrame, tree: Tree | None = None) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every document."""
    tree = tree or Tree.regular(2, 4, 5)
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select("doc_id", (F.octet_length(text) + OVERHEAD).cast("long").alias("size"), F.crc32(text).alias("text_crc32"))
    rows = assign(assign(rows, tree, "doc_id", "shard"), tree.grown(), "doc_id", "grown_shard")
    placed = ordered_positions(rows, "shard", ["doc_id", "text_crc32"], "size", "shards")
    return placed.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", F.col("row_before").alias("slot"), "grown_shard")


def write_shards(docs: DataFrame, path: str, tree: Tree | None = None) -> None:
    """The documents themselves, one folder per shard."""
    assign(docs, tree or Tree.regular(2, 4, 5), "doc_id", "_shard").write.partitionBy("_shard").parquet(path)
