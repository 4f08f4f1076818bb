"""Hierarchical weighted hash tree.

Shards are leaves of a tree of regions, racks and shards. A document descends
from the root: at every level each child draws a number from the hash of
(document id, child) and its weight, and the smallest draw wins (exponential
draws, so a child wins in proportion to its weight). Changing a weight moves
documents only into or out of the subtrees whose weights change.

The law kept is ``key``: the id and the tree decide alone. A grown tree gets its
new shard as a rack and region of its own, so every draw among old children stays
as it was and the one more shard takes rows only into itself.

Edge cases: null ids are one key like any other; repeated rows go to one shard
and get slots of their own; null and empty texts have size 1 and checksum 0; an
empty table gives an empty result. Equal texts under different ids are placed
independently, so a large group of copies spreads over all shards.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Node:
    name: str
    children: tuple["Node", ...] = ()
    shard: int = -1
    own_weight: float = 1.0

    @property
    def weight(self) -> float:
        return sum(c.weight for c in self.children) if self.children else self.own_weight


def even_tree(n_shards: int, regions: int = 2, racks: int = 2) -> Node:
    """n_shards of equal weight dealt over regions and racks; shard i keeps its place whatever else is there."""
    homes: dict[tuple[int, int], list[Node]] = {}
    for i in range(n_shards):
        home = (i % regions, i // regions % racks)
        homes.setdefault(home, []).append(Node(f"s{i}", shard=i))
    tops = []
    for r in sorted({r for r, _ in homes}):
        tops.append(Node(f"g{r}", tuple(Node(f"g{r}k{k}", tuple(v)) for (q, k), v in sorted(homes.items()) if q == r)))
    return Node("root", tuple(tops))


def grow(tree: Node, shard: int, weight: float = 1.0) -> Node:
    """One more shard, in a region and rack of its own."""
    leaf = Node(f"s{shard}", shard=shard, own_weight=weight)
    return Node(tree.name, (*tree.children, Node(f"g+{shard}", (Node(f"g+{shard}k", (leaf,)),))))


def _draw(key: Column, node: Node) -> Column:
    """Exponential draw of a rate that is the node's weight: -ln(u) / weight with u in (0, 1)."""
    digits = F.substring(F.md5(F.concat_ws("|", key, F.lit(node.name))), 1, 12)
    u = (F.conv(digits, 16, 10).cast("double") + 0.5) / float(1 << 48)
    return -F.log(u) / node.weight


def place(key: Column, tree: Node) -> Column:
    """The shard (int) that a string key descends to."""
    if not tree.children:
        return F.lit(tree.shard)
    if len(tree.children) == 1:
        return place(key, tree.children[0])
    draws = F.array(*[F.struct(_draw(key, c).alias("d"), F.lit(i).alias("i")) for i, c in enumerate(tree.children)])
    won = F.array_min(draws)["i"]
    out = place(key, tree.children[-1])
    for i, child in list(enumerate(tree.children))[-2::-1]:
        out = F.when(won == i, place(key, child)).otherwise(out)
    return out


def bin_of(key: Column, bins: int) -> Column:
    return F.conv(F.substring(F.md5(F.concat_ws("|", key, F.lit("bin"))), 1, 8), 16, 10).cast("long") % bins


def shard_documents(docs: DataFrame, tree: Node, grown: Node | None = None, id_col: str = "doc_id", text_col: str = "text", bins: int = 1024) -> DataFrame:
    """``doc_id, size, text_crc32, shard, slot, grown_shard``.

    Slots are gapless from 0 in each shard. They are counted in two steps: ranks in a
    (shard, bin) group by id, after the rows of all earlier bins of the shard; the
    table of bin offsets has at most shards x bins rows. ``bins`` is fixed, and a group
    holds the rows / (shards x bins) of the whole: no task takes a whole shard.
    """
    data = F.coalesce(docs[text_col].cast("string"), F.lit("")).cast("binary")
    key = F.coalesce(docs[id_col].cast("long").cast("string"), F.lit("null"))
    rows = docs.select(docs[id_col].cast("long").alias("doc_id"), (F.octet_length(data) + 1).cast("long").alias("size"), F.crc32(data).alias("text_crc32"), key.alias("k"))
    placed = rows.select("doc_id", "size", "text_crc32", place(F.col("k"), tree).alias("shard"), (place(F.col("k"), grown) if grown else F.lit(None).cast("int")).alias("grown_shard"), bin_of(F.col("k"), bins).alias("bin"))
    counts = placed.groupBy("shard", "bin").agg(F.count("*").alias("n"))
    before = Window.partitionBy("shard").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("shard", "bin", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("offset"))
    rank = Window.partitionBy("shard", "bin").orderBy("doc_id", "text_crc32", "size")
    ranked = placed.withColumn("r", F.row_number().over(rank) - 1)
    return ranked.join(offsets, ["shard", "bin"]).select("doc_id", "size", "text_crc32", "shard", (F.col("offset") + F.col("r")).cast("long").alias("slot"), "grown_shard")
