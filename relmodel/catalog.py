"""Relational databases as named DataFrames with declared keys (DM1-DM4, I1)."""

from __future__ import annotations

import json
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relmodel.session import importable


@dataclass(frozen=True)
class ForeignKey:
    """child.child_col points at parent.parent_col; ``name`` is the relation (DM4)."""

    name: str
    child: str
    child_col: str
    parent: str
    parent_col: str


@dataclass(frozen=True)
class TableSpec:
    """One table: key, time column and the semantic type of each column (DM3)."""

    name: str
    key: str | None
    time: str | None
    columns: dict[str, str]

    def of_kind(self, *kinds: str) -> list[str]:
        return [c for c, k in self.columns.items() if k in kinds]


@dataclass(frozen=True)
class Catalog:
    tables: dict[str, TableSpec]
    keys: tuple[ForeignKey, ...] = field(default_factory=tuple)

    def links(self, table: str) -> list[ForeignKey]:
        return [k for k in self.keys if table in (k.child, k.parent)]

    def json(self) -> str:
        """What an agent sees of the database."""
        return json.dumps({
            "tables": {t.name: {"key": t.key, "time": t.time, "columns": t.columns} for t in self.tables.values()},
            "links": [{"name": k.name, "from": f"{k.child}.{k.child_col}", "to": f"{k.parent}.{k.parent_col}"} for k in self.keys],
        }, indent=1)


def _spec(name: str, key: str | None, time: str | None, **columns: str) -> TableSpec:
    return TableSpec(name, key, time, columns)


CATALOG = Catalog(
    {t.name: t for t in (
        _spec("region", "r_regionkey", None, r_regionkey="key", r_name="categorical"),
        _spec("nation", "n_nationkey", None, n_nationkey="key", n_name="categorical", n_regionkey="key"),
        _spec("customer", "c_custkey", None, c_custkey="key", c_name="text", c_nationkey="key", c_acctbal="numerical", c_mktsegment="categorical"),
        _spec("supplier", "s_suppkey", None, s_suppkey="key", s_name="text", s_nationkey="key", s_acctbal="numerical"),
        _spec("part", "p_partkey", None, p_partkey="key", p_name="text", p_brand="categorical", p_type="categorical", p_size="numerical", p_retailprice="numerical"),
        _spec("orders", "o_orderkey", "o_orderdate", o_orderkey="key", o_custkey="key", o_orderstatus="categorical", o_totalprice="numerical", o_orderdate="timestamp", o_orderpriority="categorical"),
        _spec("lineitem", None, "l_shipdate", l_orderkey="key", l_partkey="key", l_suppkey="key", l_linenumber="numerical", l_quantity="numerical", l_extendedprice="numerical", l_discount="numerical", l_tax="numerical", l_returnflag="categorical", l_linestatus="categorical", l_shipdate="timestamp"),
        _spec("events", "event_id", "ts", event_id="key", ts="timestamp", user_id="key", event_type="categorical", value="numerical", props="nested"),
        _spec("documents", "doc_id", None, doc_id="key", text="text", lang="categorical", source="categorical", n_chars="numerical"),
        _spec("labels", "doc_id", None, doc_id="key", quality="categorical", toxic="categorical"),
    )},
    (
        ForeignKey("nation_region", "nation", "n_regionkey", "region", "r_regionkey"),
        ForeignKey("customer_nation", "customer", "c_nationkey", "nation", "n_nationkey"),
        ForeignKey("supplier_nation", "supplier", "s_nationkey", "nation", "n_nationkey"),
        ForeignKey("order_customer", "orders", "o_custkey", "customer", "c_custkey"),
        ForeignKey("line_order", "lineitem", "l_orderkey", "orders", "o_orderkey"),
        ForeignKey("line_part", "lineitem", "l_partkey", "part", "p_partkey"),
        ForeignKey("line_supplier", "lineitem", "l_suppkey", "supplier", "s_suppkey"),
        ForeignKey("event_customer", "events", "user_id", "customer", "c_custkey"),
        ForeignKey("label_document", "labels", "doc_id", "documents", "doc_id"),
    ),
)

#: Rows of lineitem have no key of their own: the digest of the whole row is one.
LINE_ID = (
    "md5(concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, CAST(l_quantity AS DECIMAL(18,2)), CAST(l_extendedprice AS DECIMAL(18,2)), "
    "CAST(l_discount AS DECIMAL(18,2)), CAST(l_tax AS DECIMAL(18,2)), l_returnflag, l_linestatus, CAST(l_shipdate AS DATE)))"
)


def load(spark: SparkSession, sf_dir: str, names=None) -> dict[str, DataFrame]:
    importable(spark)
    return {n: spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in (names or CATALOG.tables)}


def node_id(table: str, catalog: Catalog = CATALOG) -> str:
    """SQL of a table's node id as a string."""
    key = catalog.tables[table].key
    return f"CAST({key} AS STRING)" if key else LINE_ID


def check_keys(tables: dict[str, DataFrame], catalog: Catalog = CATALOG) -> DataFrame:
    """(relation, children, orphans) per declared link, one join each (DM4)."""
    out = None
    for k in catalog.keys:
        if k.child in tables and k.parent in tables:
            child = tables[k.child].select(F.col(k.child_col).alias("k"))
            lost = child.where("k IS NOT NULL").join(tables[k.parent].select(F.col(k.parent_col).alias("k")), "k", "left_anti")
            row = child.agg(F.count("*").alias("children")).crossJoin(lost.agg(F.count("*").alias("orphans"))).select(F.lit(k.name).alias("relation"), "children", "orphans")
            out = row if out is None else out.unionAll(row)
    return out
