"""Which tables, text columns, keys and link tables a database has; Parquet itself declares no keys."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StringType


@dataclass(frozen=True)
class ForeignKey:
    child: str
    child_key: str
    parent: str
    parent_key: str


@dataclass(frozen=True)
class LinkTable:
    """A table whose rows tie a row of one parent to a row of another."""

    table: str
    left_key: str
    left: str
    left_parent_key: str
    right_key: str
    right: str
    right_parent_key: str


@dataclass(frozen=True)
class SchemaSpec:
    text: dict[str, tuple[str, ...]]
    keys: tuple[ForeignKey, ...] = ()
    links: tuple[LinkTable, ...] = ()
    kinds: frozenset[str] = frozenset({"row", "fk", "nm"})
    excluded_categories: frozenset[str] = frozenset()
    excluded_pairs: frozenset[tuple[str, str]] = field(default=frozenset())

    def categories(self, table: str) -> list[str]:
        return [c for c in self.text.get(table, ()) if f"{table}.{c}" not in self.excluded_categories]

    def allows(self, a: str, b: str) -> bool:
        return (a, b) not in self.excluded_pairs and (b, a) not in self.excluded_pairs

    def without(self, category: str | None = None, relation: tuple[str, str] | None = None) -> SchemaSpec:
        """The spec that withholds a column, with every group that touches it, or one group, before any extraction."""
        return replace(self, excluded_categories=self.excluded_categories | ({category} if category else set()), excluded_pairs=self.excluded_pairs | ({relation} if relation else set()))

    def only(self, *kinds: str) -> SchemaSpec:
        return replace(self, kinds=frozenset(kinds))


def infer_text(frames: dict[str, DataFrame]) -> dict[str, tuple[str, ...]]:
    return {t: tuple(f.name for f in df.schema.fields if isinstance(f.dataType, StringType)) for t, df in frames.items()}


def load_tables(spark: SparkSession, folder: str, spec: SchemaSpec) -> dict[str, DataFrame]:
    """The scans of a spec's tables; later projections prune them."""
    names = {*spec.text, *(k.child for k in spec.keys), *(k.parent for k in spec.keys), *(k.table for k in spec.links)}
    return {t: spark.read.parquet(f"{folder}/{t}.parquet") for t in sorted(names)}


_NATION = ForeignKey("nation", "n_regionkey", "region", "r_regionkey")
_CUSTOMER = ForeignKey("customer", "c_nationkey", "nation", "n_nationkey")

MINI = SchemaSpec({"region": ("r_name",), "nation": ("n_name",), "customer": ("c_name", "c_mktsegment")}, (_NATION, _CUSTOMER))

COMMERCE = SchemaSpec(
    {
        "region": ("r_name",), "nation": ("n_name",), "customer": ("c_name", "c_mktsegment"), "supplier": ("s_name",),
        "part": ("p_name", "p_brand", "p_type"), "orders": ("o_orderstatus", "o_orderpriority"), "lineitem": ("l_returnflag", "l_linestatus"),
    },
    (_NATION, _CUSTOMER, ForeignKey("supplier", "s_nationkey", "nation", "n_nationkey"), ForeignKey("orders", "o_custkey", "customer", "c_custkey"), ForeignKey("lineitem", "l_partkey", "part", "p_partkey")),
    (LinkTable("lineitem", "l_partkey", "part", "p_partkey", "l_suppkey", "supplier", "s_suppkey"),),
)

CORPUS = SchemaSpec({"documents": ("text", "lang", "source"), "conversations": ("text", "role")})
