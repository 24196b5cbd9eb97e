"""The region tree: every leaf region and its ancestors, level 0 being the root."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows of the ancestor table up to which it is broadcast; beyond, joins with it are plain equi-joins.
BROADCAST_ROWS = 1_000_000


@dataclass
class RegionTree:
    """`wide` has one row a leaf: leaf_id and level_0 .. level_L, the last being leaf_id itself."""

    wide: DataFrame
    levels: int
    checked: bool | None = None

    @classmethod
    def from_levels(cls, df: DataFrame, columns: list[str]) -> "RegionTree":
        """A tree from nested columns under a root: each level's node is the path of its column and those above."""
        paths, nodes = [], [F.lit("all").alias("level_0")]
        for k, c in enumerate(columns, 1):
            paths.append(F.col(c).cast("string"))
            nodes.append(F.concat_ws("/", *paths).alias(f"level_{k}"))
        wide = df.select(*nodes).distinct()
        return cls(wide.withColumn("leaf_id", F.col(f"level_{len(columns)}")), len(columns) + 1)

    def long(self) -> DataFrame:
        """(leaf_id, level, node_id): each leaf with all its ancestors, itself included."""
        return self.wide.select("leaf_id", F.explode(F.array(*[F.struct(F.lit(k).alias("level"), F.col(f"level_{k}").alias("node_id")) for k in range(self.levels)])).alias("x")).select("leaf_id", "x.level", "x.node_id")

    def nodes(self) -> DataFrame:
        """(level, node_id, parent_id), the root's parent being null."""
        pairs = F.array(*[F.struct(F.lit(k).alias("level"), F.col(f"level_{k}").alias("node_id"), (F.col(f"level_{k - 1}") if k else F.lit(None).cast("string")).alias("parent_id")) for k in range(self.levels)])
        return self.wide.select(F.explode(pairs).alias("x")).select("x.*").distinct()

    def ancestor(self, df: DataFrame, level: int, leaf_col: str = "leaf_id") -> DataFrame:
        """Add node_id: the ancestor at the level of each row's leaf."""
        return df.join(self.small(self.wide.select(F.col("leaf_id").alias(leaf_col), F.col(f"level_{level}").alias("node_id"))), leaf_col)

    def small(self, table: DataFrame) -> DataFrame:
        """Mark a table of the tree for broadcast if its size has been checked."""
        if self.checked is None:  # counted once a tree
            self.checked = self.wide.limit(BROADCAST_ROWS // self.levels + 1).count() * self.levels <= BROADCAST_ROWS
        return F.broadcast(table) if self.checked else table

    def restrict(self, nodes: list[str]) -> "RegionTree":
        """Only the leaves below the given level-1 nodes; the root is then their union."""
        return RegionTree(self.wide.where(F.col("level_1").isin(*nodes)), self.levels)

    def cut(self, level: int) -> "RegionTree":
        """The tree down to a level only. Leaves below share its nodes, so leaf ids stay those of the groups."""
        return RegionTree(self.wide, level + 1)

    def validate(self, groups: DataFrame | None = None) -> DataFrame:
        """(check, bad): leaves with two paths, nodes with two parents, trees with more than one root. All must be 0.

        With the public groups (group_id, leaf_id) also: groups in two leaves, groups in a leaf that the tree lacks, and
        nodes whose number of groups is not the sum of their children's.
        """
        nodes = self.nodes()
        checks = [("leaf_paths", self.wide.groupBy("leaf_id").count().where("count > 1")), ("node_parents", nodes.groupBy("level", "node_id").count().where("count > 1")), ("roots", nodes.where("level = 0").select("node_id").distinct().groupBy().count().where("count > 1"))]
        if groups is not None:
            leaves = groups.groupBy("leaf_id").agg(F.count(F.lit(1)).alias("n"))
            g = self.long().join(leaves, "leaf_id").groupBy("level", "node_id").agg(F.sum("n").alias("g"))
            up = g.join(nodes.where("parent_id is not null"), ["level", "node_id"]).select((F.col("level") - 1).alias("level"), F.col("parent_id").alias("node_id"), "g")
            sums = up.unionByName(g.where(F.col("level") < self.levels - 1).withColumn("g", -F.col("g"))).groupBy("level", "node_id").agg(F.sum("g").alias("gap"))
            checks += [("group_leaves", groups.groupBy("group_id").agg(F.countDistinct("leaf_id").alias("n")).where("n > 1")), ("unknown_leaves", groups.join(self.wide.select("leaf_id"), "leaf_id", "left_anti")), ("group_sums", sums.where("gap <> 0"))]
        out = None
        for name, df in checks:
            row = df.agg(F.count(F.lit(1)).alias("bad")).select(F.lit(name).alias("check"), "bad")
            out = row if out is None else out.unionByName(row)
        return out
