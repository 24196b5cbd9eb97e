"""Experiment workloads: what is a group, what is an entity, and the region tree, on the given tables.

Each workload is written once in SQL that Spark and other engines read alike; the exact oracles use the same text.
`groups` yields (group_id, leaf columns), `entities` yields group_id, one row an entity.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import profile
from ..operators.tree import RegionTree


@dataclass(frozen=True)
class Workload:
    name: str
    groups: str
    entities: str
    levels: tuple[str, ...]
    ceiling: int
    tables: tuple[str, ...]
    stands_for: str = ""

    def query(self, spark: SparkSession, sf_dir: str, sql: str) -> DataFrame:
        """Run the text on the tables of the folder; no name is left in the session."""
        used = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in self.tables}
        text = re.sub(rf"\b(from|join) ({'|'.join(self.tables)})\b", r"\1 [[\2]]", sql).replace("{", "{{").replace("}", "}}").replace("[[", "{").replace("]]", "}")
        return spark.sql(text, **{t: df for t, df in used.items() if f"{{{t}}}" in text})

    def placed(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        """(group_id, leaf_id, columns of the levels) of the public groups."""
        leaf = F.concat_ws("/", *[F.col(c).cast("string") for c in self.levels]) if self.levels else F.lit("all")
        return self.query(spark, sf_dir, self.groups).select("group_id", leaf.alias("leaf_id"), *self.levels)

    def load(self, spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, RegionTree]:
        """(entities, groups with leaf_id, tree)."""
        groups = self.placed(spark, sf_dir)
        tree = RegionTree.from_levels(groups, list(self.levels))
        return self.query(spark, sf_dir, self.entities), groups.select("group_id", "leaf_id"), tree

    def histogram(self, spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, RegionTree]:
        """(exact histogram of all nodes, public counts, tree)."""
        entities, groups, tree = self.load(spark, sf_dir)
        sizes = profile.clamp_sizes(profile.group_sizes(entities, groups), self.ceiling)
        return profile.rollup_histogram(profile.leaf_histogram(sizes), tree), profile.public_counts(groups, tree), tree


_PLACE = "customer c join nation n on c.c_nationkey = n.n_nationkey join region r on n.n_regionkey = r.r_regionkey"
_CUSTOMERS = f"select c.c_custkey as group_id, r.r_name as region, n.n_name as nation from {_PLACE}"
_BUYS = "orders o join lineitem l on l.l_orderkey = o.o_orderkey"
_PART_TYPE = "select o.o_custkey as group_id from {buys} join part p on p.p_partkey = l.l_partkey where p.p_type = '{kind}'"
_HOST = "split_part(regexp_replace(url, '^[a-z]+://', ''), '/', 1)"
_SECTION = f"{_HOST} || '/' || split_part(regexp_replace(url, '^[a-z]+://', ''), '/', 2)"
PART_TYPES = ("ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD")

WORKLOADS: dict[str, Workload] = {
    w.name: w
    for w in (
        Workload("w1", f"select o.o_orderkey as group_id, r.r_name as region, n.n_name as nation from orders o join {_PLACE.replace('customer c join', 'customer c on o.o_custkey = c.c_custkey join')}", "select l_orderkey as group_id from lineitem", ("region", "nation"), 64, ("orders", "lineitem", "customer", "nation", "region"), "housing"),
        Workload("w3", f"select distinct concat(l.l_suppkey, ':', n.n_name) as group_id, r.r_name as region, n.n_name as nation from {_BUYS} join {_PLACE.replace('customer c join', 'customer c on o.o_custkey = c.c_custkey join')}", f"select concat(l.l_suppkey, ':', n.n_name) as group_id from {_BUYS} join customer c on o.o_custkey = c.c_custkey join nation n on c.c_nationkey = n.n_nationkey", ("region", "nation"), 256, ("orders", "lineitem", "customer", "nation", "region"), "taxi"),
        Workload("w4", _CUSTOMERS, f"select o.o_custkey as group_id from {_BUYS}", ("region", "nation"), 256, ("orders", "lineitem", "customer", "nation", "region"), "dense race counts"),
        Workload("w5", _CUSTOMERS, f"select o.o_custkey as group_id from {_BUYS} where l.l_returnflag = 'R' and l.l_discount >= 0.09 and o.o_orderpriority = '1-URGENT'", ("region", "nation"), 64, ("orders", "lineitem", "customer", "nation", "region"), "sparse race counts"),
        Workload("w9", f"select o.o_orderkey as group_id, r.r_name as region, n.n_name as nation, c.c_mktsegment as segment from orders o join {_PLACE.replace('customer c join', 'customer c on o.o_custkey = c.c_custkey join')}", "select l_orderkey as group_id from lineitem", ("region", "nation", "segment"), 64, ("orders", "lineitem", "customer", "nation", "region"), "many leaves"),
        Workload("w16", "select doc_id as group_id, lang, source from documents", "select doc_id as group_id from (select doc_id, explode(split(trim(regexp_replace(text, '[ \\t\\n\\r]+', ' ')), ' ')) as w from documents) t where w <> ''", ("lang", "source"), 32768, ("documents",), "heavy tail"),
        Workload("w17", "select user_id || ':' || cast(cast(ts as date) as string) as group_id, date_format(date_trunc('week', ts), 'yyyy-MM-dd') as week, cast(cast(ts as date) as string) as day from events group by user_id, cast(ts as date), date_trunc('week', ts)", "select user_id || ':' || cast(cast(ts as date) as string) as group_id from events", ("week", "day"), 64, ("events",), "time"),
        Workload("w18", "select p_partkey as group_id, p_brand as brand, p_type as type from part", "select l_partkey as group_id from lineitem", ("brand", "type"), 128, ("part", "lineitem"), "products"),
        Workload("w19", "select distinct conv_id as group_id from conversations", "select conv_id as group_id from conversations", (), 64, ("conversations",), "no hierarchy"),
        Workload("w19b", "select md5(text) as group_id from documents group by md5(text)", "select md5(text) as group_id from documents", (), 64, ("documents",), "clusters of equal texts"),
        Workload("w20", "select s.s_suppkey as group_id, r.r_name as region, n.n_name as nation from supplier s join nation n on s.s_nationkey = n.n_nationkey join region r on n.n_regionkey = r.r_regionkey", "select l_suppkey as group_id from lineitem", ("region", "nation"), 2048, ("supplier", "lineitem", "nation", "region"), "large sizes"),
        Workload("w21", "select distinct label as group_id from embeddings", "select label as group_id from embeddings", (), 4096, ("embeddings",), "label clusters"),
        Workload("w21b", "select distinct substring_index(regexp_replace(url, '^[a-z]+://', ''), '/', 1) as group_id from pages", "select substring_index(regexp_replace(url, '^[a-z]+://', ''), '/', 1) as group_id from pages", (), 4096, ("pages",), "hosts"),
        Workload("w21c", f"select distinct {_SECTION} as group_id, {_HOST} as host from pages", f"select {_SECTION} as group_id from pages", ("host",), 4096, ("pages",), "sections of hosts"),
        Workload("w21d", "select distinct quality || ':' || toxic as group_id from labels", "select quality || ':' || toxic as group_id from labels", (), 100_000, ("labels",), "clusters of labels"),
        *(Workload(f"w6_{t.lower()}", _CUSTOMERS, _PART_TYPE.format(buys=_BUYS, kind=t), ("region", "nation"), 128, ("orders", "lineitem", "customer", "nation", "region", "part"), f"category {t}") for t in PART_TYPES),
    )
}
