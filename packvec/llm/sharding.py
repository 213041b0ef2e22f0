"""Operator 1: rows into shards by a weighted hash tree of regions, racks and shards.

Each node of a level is drawn by an exponential race: the key's hash at that node gives u in (0, 1), the node's time is
-ln(u) / weight, and the earliest wins, which happens with a probability in proportion to the weight. A leaf added
later races once, at the root, against the unchanged subtrees. If it wins, the key goes there; if not, the key
descends as before. So a row moves only into the new shard, and subtrees whose weight stays keep every row.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Groups that the rows of a shard are numbered in; the numbering of a group is one task's work.
NUMBERING_GROUPS = 256


@dataclass(frozen=True)
class HashTree:
    """regions[r][k] is the number of shards in rack k of region r, numbered from 0 in that order.

    added: weights of leaves added later, in order; they take the next shard numbers. Weights: racks and shards count
    1 for each shard below them unless shard_weights says otherwise.
    """

    regions: tuple[tuple[int, ...], ...]
    shard_weights: dict[int, float] = field(default_factory=dict)
    added: tuple[float, ...] = ()

    @property
    def base(self) -> int:
        return sum(map(sum, self.regions))

    @property
    def shards(self) -> int:
        return self.base + len(self.added)

    def grown(self, weight: float = 1.0) -> HashTree:
        return HashTree(self.regions, self.shard_weights, (*self.added, weight))

    def leaves(self) -> list[list[list[tuple[int, float]]]]:
        out, shard = [], 0
        for racks in self.regions:
            out.append([])
            for n in racks:
                out[-1].append([(s, self.shard_weights.get(s, 1.0)) for s in range(shard, shard + n)])
                shard += n
        return out


def tree_of(n: int, fan: int = 5) -> HashTree:
    """n shards: racks of fan shards, two regions of racks, the last ones smaller."""
    racks = [min(fan, n - i) for i in range(0, n, fan)]
    half = (len(racks) + 1) // 2
    return HashTree(tuple(tuple(x) for x in (racks[:half], racks[half:]) if x))


def draw(key: Column, node: Column) -> Column:
    """A number in (0, 1) from the key and the node's number: the upper 53 bits of a hash."""
    return (F.shiftrightunsigned(F.xxhash64(node.cast("long"), key), 11).cast("double") + F.lit(0.5)) * F.lit(2.0**-53)


def first(key: Column, node: Column, weights: Column, at: Column, n: int) -> Column:
    """(t, i) of the earliest of runners 0 .. n - 1, whose nodes are numbered from node on and whose weights begin at `at`. Weight 0 never wins."""
    def run(i: Column) -> Column:
        w = F.get(weights, at + i)
        return F.struct(F.when(w > 0, -F.ln(draw(key, node + i)) / w).otherwise(F.lit(float("inf"))).alias("t"), i.alias("i"))

    return F.array_min(F.transform(F.sequence(F.lit(0), F.lit(n - 1)), run))


#: Node numbers of a level begin at its multiple of this: regions, racks, leaves, leaves added later.
LEVEL = 1 << 40


def with_shard(df: DataFrame, key: str, tree: HashTree, out: str, grown: str | None = None) -> DataFrame:
    """df with the shard of its key, one level after the other; grown: the shard if one more leaf of weight 1 is added.

    Null keys count as ''.
    """
    leaves = tree.leaves()
    racks, fan = max(map(len, leaves)), max(len(y) for x in leaves for y in x)
    slots = [[leaves[i][j][n] if j < len(leaves[i]) and n < len(leaves[i][j]) else (0, 0.0) for j in range(racks) for n in range(fan)] for i in range(len(leaves))]
    literal = lambda values: F.array(*map(F.lit, values))
    by_leaf = literal([w for x in slots for _, w in x])
    by_rack = literal([float(sum(w for _, w in x[j * fan : (j + 1) * fan])) for x in slots for j in range(racks)])
    by_region = literal([float(sum(w for _, w in x)) for x in slots])
    k = F.col("_pv_k")
    step = df.withColumn("_pv_k", F.coalesce(F.col(key).cast("string"), F.lit("")))
    step = step.withColumn("_pv_region", first(k, F.lit(0), by_region, F.lit(0), len(leaves)))
    rack = F.col("_pv_region.i") * racks
    step = step.withColumn("_pv_rack", rack + first(k, F.lit(LEVEL) + rack, by_rack, rack, racks)["i"])
    leaf = F.col("_pv_rack") * fan
    step = step.withColumn("_pv_leaf", F.get(literal([s for x in slots for s, _ in x]), leaf + first(k, F.lit(2 * LEVEL) + leaf, by_leaf, leaf, fan)["i"]))

    def landed(added: tuple[float, ...]) -> Column:
        if not added:
            return F.col("_pv_leaf").cast("int")
        late = first(k, F.lit(3 * LEVEL), literal([float(w) for w in added]), F.lit(0), len(added))
        return F.when(late["t"] < F.col("_pv_region.t"), F.lit(tree.base) + late["i"]).otherwise(F.col("_pv_leaf")).cast("int")

    step = step.withColumn(out, landed(tree.added))
    if grown:
        step = step.withColumn(grown, landed((*tree.added, 1.0)))
    return step.drop("_pv_k", "_pv_region", "_pv_rack", "_pv_leaf")


def assign(df: DataFrame, tree: HashTree, key: str = "doc_id", shard: str = "shard", slot: str = "slot", grown: str | None = None) -> DataFrame:
    """df with its shard, a number within the shard without gaps from 0 and, if named, the shard that one more would give.

    Numbering needs no task that sees a whole shard: rows are numbered within groups of (shard, hash of key), and each
    group starts where the ones before it end. The counts table has NUMBERING_GROUPS rows a shard at most, whatever the
    input, so it may be broadcast. Edge cases: null keys all share the shard of ''; repeated rows get slots of their
    own; an empty table gives an empty result; other columns pass through, those named like the results are replaced.
    """
    def group(c: str) -> Column:
        return F.pmod(F.xxhash64(F.coalesce(F.col(c).cast("string"), F.lit(""))), F.lit(NUMBERING_GROUPS)).cast("int")

    results = [c for c in (shard, slot, grown) if c]
    base = df.select(*[c for c in df.columns if c not in results])
    counted = with_shard(base.select(F.col(key).alias("_pv_key")), "_pv_key", tree, "_pv_s").groupBy("_pv_s", group("_pv_key").alias("_pv_g")).agg(F.count(F.lit(1)).alias("_pv_n"))
    begins = counted.select(F.col("_pv_s"), F.col("_pv_g").alias("_pv_h"), (F.sum("_pv_n").over(Window.partitionBy("_pv_s").orderBy("_pv_g")) - F.col("_pv_n")).alias("_pv_begin"))
    placed = with_shard(base, key, tree, shard, grown).withColumn("_pv_g", group(key))
    numbered = placed.withColumn("_pv_i", F.row_number().over(Window.partitionBy(shard, "_pv_g").orderBy(F.col(key).asc_nulls_first())) - 1)
    # A left join, as an inner one would compute shards twice to drop null ones.
    joined = numbered.join(F.broadcast(begins), (F.col(shard) == F.col("_pv_s")) & (F.col("_pv_g") == F.col("_pv_h")), "left")
    return joined.select(*base.columns, *[F.col(c) for c in (shard, grown) if c], (F.col("_pv_begin") + F.col("_pv_i")).cast("long").alias(slot))
