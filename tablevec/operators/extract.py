"""Text values and typed links of a database."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tablevec.operators.relational import broadcast_if_small
from tablevec.plans.stages import Stages
from tablevec.spec import ForeignKey, LinkTable, SchemaSpec


def _real(c: str) -> Column:
    return F.col(c).isNotNull() & (F.col(c) != "")


def _union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def extract_values(frames: dict[str, DataFrame], spec: SchemaSpec, unique: str = "per_column") -> DataFrame:
    """(category, value): each text once for each column it is in; nulls and empty texts are no values."""
    if unique != "per_column":
        raise ValueError("a node for each occurrence would hold no relation together; values are unique in a column")
    parts = []
    for table, df in frames.items():
        columns = spec.categories(table)
        if columns:  # one scan of a table gives all its columns
            pairs = F.array(*(F.struct(F.lit(f"{table}.{c}").alias("category"), F.col(c).alias("value")) for c in columns))
            parts.append(df.select(F.explode(pairs).alias("p")).select("p.*").where(_real("value")))
    return _union(parts).distinct()


def dense_ids(df: DataFrame, order: list[str], name: str = "node_id") -> DataFrame:
    """Adds ids 0, 1, 2, ... in the given order: sorted ranges get offsets, so no task sees all rows."""
    stages = Stages(df.sparkSession, "ids")
    ranged = df.repartitionByRange(*order).sortWithinPartitions(*order)
    kept = stages.keep(ranged.select("*", F.spark_partition_id().alias("_part"), F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1).alias("_at")))
    sizes = sorted((r["_part"], r["count"]) for r in kept.groupBy("_part").count().collect())  # one row for each partition
    offsets, total = [], 0
    for part, n in sizes:
        offsets.append((part, total))
        total += n
    starts = df.sparkSession.createDataFrame(offsets, "_part int, _start long")
    return kept.join(F.broadcast(starts), "_part").select(*df.columns, (F.col("_start") + F.col("_at")).alias(name))


#: A link of columns: its relation, and category and column of each end.
Pair = tuple[str, str, str, str, str]


def _pairs(a: list[tuple[str, str]], b: list[tuple[str, str]], kind: str, spec: SchemaSpec) -> list[Pair]:
    """The links from columns (category, column) of one side to those of the other."""
    return [(f"{kind}:{ca}>{cb}", ca, x, cb, y) for ca, x in a for cb, y in b if spec.allows(ca, cb)]


def _exploded(df: DataFrame, pairs: list[Pair]) -> DataFrame | None:
    """(rel, src_category, src, dst_category, dst), each link once; until they are distinct, links carry a number for their names."""
    if not pairs:
        return None
    ends = F.array(*(F.struct(F.lit(i).alias("k"), F.col(x).alias("src"), F.col(y).alias("dst")) for i, (_, _, x, _, y) in enumerate(pairs)))
    found = df.select(F.explode(ends).alias("p")).select("p.*").where(_real("src") & _real("dst")).distinct()
    name = lambda at: F.get(F.array(*(F.lit(p[at]) for p in pairs)), F.col("k"))
    return found.select(name(0).alias("rel"), name(1).alias("src_category"), "src", name(3).alias("dst_category"), "dst")


def links_row(frames: dict[str, DataFrame], table: str, spec: SchemaSpec) -> DataFrame | None:
    """Links between the text columns of one row."""
    columns = spec.categories(table)
    named = [(f"{table}.{c}", c) for c in columns]
    return _exploded(frames[table], [p for i in range(len(named) - 1) for p in _pairs([named[i]], named[i + 1 :], "row", spec)])


def _side(df: DataFrame, table: str, keys: list[str], spec: SchemaSpec, tag: str) -> tuple[DataFrame, list[tuple[str, str]]]:
    columns = spec.categories(table)
    kept = df.select(*(F.col(k).alias(f"{tag}_{k}") for k in keys), *(F.col(c).alias(f"{tag}{c}") for c in columns))
    return kept, [(f"{table}.{c}", f"{tag}{c}") for c in columns]


def links_fk(frames: dict[str, DataFrame], key: ForeignKey, spec: SchemaSpec) -> DataFrame | None:
    """Links from every text column of the child to every one of the parent; one join gives all groups.

    Key and texts are made distinct first, so a large child joins once for each different row of texts.
    """
    child, a = _side(frames[key.child], key.child, [key.child_key], spec, "c")
    parent, b = _side(frames[key.parent], key.parent, [key.parent_key], spec, "p")
    pairs = _pairs(a, b, "fk", spec)
    return None if not pairs else _exploded(child.distinct().join(broadcast_if_small(parent, 10_000), F.col(f"c_{key.child_key}") == F.col(f"p_{key.parent_key}")), pairs)


def links_nm(frames: dict[str, DataFrame], link: LinkTable, spec: SchemaSpec) -> DataFrame | None:
    """Links between the text columns of two parents that a link table ties; key pairs are made distinct first."""
    ties = frames[link.table].select(F.col(link.left_key).alias("_l"), F.col(link.right_key).alias("_r")).distinct()
    left, a = _side(frames[link.left], link.left, [link.left_parent_key], spec, "a")
    right, b = _side(frames[link.right], link.right, [link.right_parent_key], spec, "b")
    pairs = _pairs(a, b, "nm", spec)
    if not pairs:
        return None
    return _exploded(ties.join(left, F.col("_l") == F.col(f"a_{link.left_parent_key}")).join(right, F.col("_r") == F.col(f"b_{link.right_parent_key}")), pairs)


def extract_links(frames: dict[str, DataFrame], spec: SchemaSpec) -> DataFrame:
    """All groups of a spec as (rel, src_category, src, dst_category, dst), each link once, without mirrors."""
    found: list[DataFrame | None] = []
    if "row" in spec.kinds:
        found += [links_row(frames, t, spec) for t in spec.text]
    if "fk" in spec.kinds:
        found += [links_fk(frames, k, spec) for k in spec.keys]
    if "nm" in spec.kinds:
        found += [links_nm(frames, k, spec) for k in spec.links]
    parts = [f for f in found if f is not None]
    if not parts:
        spark = next(iter(frames.values())).sparkSession
        return spark.createDataFrame([], "rel string, src_category string, src string, dst_category string, dst string")
    return _union(parts)


def links_of_new_rows(frames: dict[str, DataFrame], table: str, rows: DataFrame, spec: SchemaSpec) -> DataFrame:
    """The links that new rows of one table can add: of its own rows, and of relations that it takes part in.

    `frames` holds all rows, the new ones included; a table that refers to itself is read whole for that relation.
    """
    itself = [k for k in spec.keys if k.child == k.parent == table]
    keys = tuple(k for k in spec.keys if table in (k.child, k.parent) and k not in itself)
    links = tuple(k for k in spec.links if table in (k.table, k.left, k.right))
    twice = tuple(k for k in links if (k.table, k.left, k.right).count(table) > 1)
    own = {table: spec.text[table]} if table in spec.text else {}
    batch = {**frames, table: rows}
    found = []
    if "row" in spec.kinds and own:
        found.append(links_row(batch, table, spec))
    if "fk" in spec.kinds:
        found += [links_fk(batch, k, spec) for k in keys] + [links_fk(frames, k, spec) for k in itself]
    if "nm" in spec.kinds:
        found += [links_nm(frames if k in twice else batch, k, spec) for k in links]
    parts = [f for f in found if f is not None]
    if not parts:
        return rows.sparkSession.createDataFrame([], "rel string, src_category string, src string, dst_category string, dst string")
    return _union(parts).distinct()


def mirrored(links: DataFrame) -> DataFrame:
    """The links with their mirrors, from one scan: (rel, rel_inv, src_category, src, dst_category, dst)."""
    there = F.struct("rel", F.lit(False).alias("rel_inv"), "src_category", "src", "dst_category", "dst")
    back = F.struct("rel", F.lit(True).alias("rel_inv"), F.col("dst_category").alias("src_category"), F.col("dst").alias("src"), F.col("src_category").alias("dst_category"), F.col("src").alias("dst"))
    return links.select(F.explode(F.array(there, back)).alias("p")).select("p.*")


def numbered(links: DataFrame, nodes: DataFrame) -> DataFrame:
    """Mirrored links on node ids: (rel, rel_inv, src, dst)."""
    a = nodes.select(F.col("category").alias("src_category"), F.col("value").alias("src"), F.col("node_id").alias("a"))
    b = nodes.select(F.col("category").alias("dst_category"), F.col("value").alias("dst"), F.col("node_id").alias("b"))
    both = links.join(a, ["src_category", "src"]).join(b, ["dst_category", "dst"])
    there, back = F.struct("rel", F.lit(False).alias("rel_inv"), F.col("a").alias("src"), F.col("b").alias("dst")), F.struct("rel", F.lit(True).alias("rel_inv"), F.col("b").alias("src"), F.col("a").alias("dst"))
    return both.select(F.explode(F.array(there, back)).alias("p")).select("p.*")


def expand_json(df: DataFrame, column: str, schema: str, *keep: str) -> DataFrame:
    """Rows of a JSON list column, one for each entry; a row with none, or with broken text, keeps one null entry."""
    parsed = F.from_json(F.col(column), f"array<{schema}>")
    return df.select(*keep, F.explode_outer(parsed).alias("entry"))


def _run(text: Column, n: int):
    return lambda i: F.substr(text, i, F.lit(n))


def containment_links(texts: DataFrame, passages: DataFrame) -> DataFrame:
    """(src, dst): texts that contain a passage; null and empty passages are in none.

    A passage meets texts by its first 24 characters, a shorter one by all of it. Runs of characters are cut from pieces
    of a text, so long texts are not walked from their start for each run, and go with a digest instead of the text.
    """
    size, piece = 24, 512
    keyed = texts.where("src != ''").select(F.md5("src").alias("src_key"), "src").distinct()
    held = passages.where("dst != ''").select(F.md5("dst").alias("dst_key"), "dst", F.substring("dst", 1, size).alias("head")).distinct()
    lengths = sorted(r[0] for r in held.select(F.length("head")).distinct().collect())  # at most `size` numbers
    if not lengths:
        return keyed.limit(0).select("src", F.col("src").alias("dst"))

    def runs(text: Column) -> Column:
        none = F.array().cast("array<string>")
        each = [F.when(F.length(text) >= n, F.transform(F.sequence(F.lit(1), F.least(F.lit(piece), F.length(text) - n + 1)), _run(text, n))).otherwise(none) for n in lengths]
        return F.concat(*each)

    starts = F.sequence(F.lit(1), F.length("src"), F.lit(piece))
    cut = F.flatten(F.transform(F.transform(starts, lambda at: F.substr(F.col("src"), at, F.lit(piece + size - 1))), runs))
    grams = keyed.select("src_key", F.explode(F.array_distinct(cut)).alias("head"))
    near = grams.join(broadcast_if_small(held.select("head", "dst_key"), 100_000), "head").select("src_key", "dst_key").distinct()
    both = near.join(held.select("dst_key", "dst"), "dst_key").join(keyed, "src_key")
    return both.where(F.contains("src", "dst")).select("src", "dst")


def participating(values: DataFrame, links: DataFrame) -> DataFrame:
    """The values that are in a link."""
    ends = links.select(F.col("src_category").alias("category"), F.col("src").alias("value")).union(links.select("dst_category", "dst")).distinct()
    return values.join(ends, ["category", "value"], "left_semi")


def orphans(values: DataFrame, links: DataFrame) -> DataFrame:
    ends = links.select(F.col("src_category").alias("category"), F.col("src").alias("value")).union(links.select("dst_category", "dst")).distinct()
    return values.join(ends, ["category", "value"], "left_anti")


def fraction(frames: dict[str, DataFrame], table: str, key: str, below: int) -> dict[str, DataFrame]:
    """The database with the rows of one table whose key is below a cut."""
    return {t: df.where(F.col(key) < below) if t == table else df for t, df in frames.items()}
