"""Sharding by a weighted hash tree: region, rack, shard.

At each level the children of the chosen node draw for a document: child c with weight w draws
-ln(u)/w with u hashed from (document, c), and the least draw wins, which gives each child its share
of the weights. A draw depends on nothing but the document, the child and the child's own weight, so
raising one weight can only move rows towards that child, and all movement stays in subtrees whose
weights change.

Only DataFrame functions run here.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from assetmill.operators.ranks import order_digits, place_in_group
from assetmill.plans.scratch import Scratch

#: Bytes that a row takes besides its text.
ROW_BYTES = 16


@dataclass(frozen=True)
class Tree:
    """Shards of weight one by region and rack: ``regions[i][j]`` lists shard numbers of rack j."""

    regions: tuple[tuple[tuple[int, ...], ...], ...]

    @classmethod
    def balanced(cls, shards: int, regions: int, racks: int) -> "Tree":
        """``shards`` dealt evenly over ``regions`` of ``racks`` each."""
        per = shards // (regions * racks)
        if per * regions * racks != shards:
            raise ValueError("shards must fill all racks")
        it = iter(range(shards))
        return cls(tuple(tuple(tuple(next(it) for _ in range(per)) for _ in range(racks)) for _ in range(regions)))

    def grown(self) -> "Tree":
        """One more shard, in a region of its own: no old subtree changes its weight, so rows move into
        the new shard only."""
        n = 1 + max(s for r in self.regions for k in r for s in k)
        return Tree(self.regions + (((n,),),))

    def shard_of(self, key: Column) -> Column:
        """The shard of a row with this key."""
        # Nodes in breadth order; each lists its children as (place in the list, name, weight).
        nodes, kids, leaf = [("t", self.regions)], [], {}
        for path, node in nodes:
            if isinstance(node, int):
                leaf[len(kids)] = node
                kids.append([])
                continue
            first = len(nodes)
            nodes += [(f"s{c}" if isinstance(c, int) else f"{path}.{i}", c) for i, c in enumerate(node)]
            kids.append([(first + i, nodes[first + i][0], _weight(c)) for i, c in enumerate(node)])
        shape = "array<struct<at:int,name:string,weight:double>>"
        table = F.array(*(F.array(*(F.struct(F.lit(at).alias("at"), F.lit(name).alias("name"), F.lit(float(w)).alias("weight")) for at, name, w in k)) if k else F.array().cast(shape) for k in kids))

        def draw(child: Column) -> Column:
            bits = F.conv(F.substring(F.md5(F.concat(key, F.lit("/"), child["name"])), 1, 13), 16, 10).cast("double")
            return F.struct((-F.log((bits + 0.5) / F.lit(float(2**52))) / child["weight"]).alias("draw"), child["at"].alias("at"))

        at = F.lit(0)
        for _ in ("region", "rack", "shard"):
            at = F.array_min(F.transform(F.get(table, at), draw))["at"]
        return F.get(F.array(*(F.lit(leaf.get(i, -1)) for i in range(len(nodes)))), at)


def _weight(node) -> int:
    return 1 if isinstance(node, int) else sum(map(_weight, node))


#: Production layout: 40 shards over five regions of two racks.
LAYOUT = Tree.balanced(40, 5, 2)


def shard(docs: DataFrame, scratch: Scratch, tree: Tree = LAYOUT) -> DataFrame:
    """One row per document: doc_id, size, text_crc32, law, shard, slot, grown_shard.

    The law is ``key``: doc_id and the tree decide. Slots count from 0 without gaps in each shard, in
    the order of a hash of doc_id, ties by doc_id, size and checksum. Null texts have no bytes and the
    checksum of the empty text; a null doc_id is one more key; equal rows get slots of their own; an
    empty table gives no rows. Columns other than doc_id and text are not read.
    """
    key = F.coalesce(F.col("doc_id").cast("string"), F.lit("null"))
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", (F.octet_length(text) + ROW_BYTES).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.md5(F.concat(F.lit("slot:"), key)).alias("turn"), tree.shard_of(key).cast("int").alias("shard"), tree.grown().shard_of(key).cast("int").alias("grown_shard"))
    rows = scratch.keep(rows, "rows")
    most = rows.groupBy("shard").count().agg(F.max("count")).first()[0] or 0
    placed = place_in_group(rows, ["shard"], "turn", ["doc_id", "size", "text_crc32"], order_digits(most), rank="slot")
    return placed.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", F.col("slot").cast("long").alias("slot"), "grown_shard")
