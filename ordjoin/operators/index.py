"""Join groups: rows of a child by join key, in the order of their optimum or of variables; saving them for later."""

from __future__ import annotations

import json
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ordjoin.operators.dp import Prepared, with_all
from ordjoin.plans.jointree import JoinTree
from ordjoin.plans.model import Atom, ConjunctiveQuery
from ordjoin.plans.ranking import Rank


def sort_groups(p: Prepared, i: int, by: Sequence[Column], most: int | None = None) -> DataFrame:
    """Relation i with ``_pos``, the place in its group from 1; with ``most`` only the first places (a group limit)."""
    df, keys = with_all(p.frames[i], p.tree.shared(i))
    out = df.withColumn("_pos", F.row_number().over(Window.partitionBy(*keys).orderBy(*by)))
    return out.where(F.col("_pos") <= most) if most is not None else out


def group_sizes(p: Prepared, i: int) -> DataFrame:
    df, keys = with_all(p.frames[i], p.tree.shared(i))
    return df.groupBy(*keys).agg(F.count(F.lit(1)).alias("size"))


def save_prepared(p: Prepared, path: str, buckets: int | None = None, name: str | None = None) -> None:
    """Write reduced relations, clustered by join key and sorted by optimum inside; with ``name`` as bucketed tables."""
    spark = p.frames[p.root].sparkSession
    tables: dict[int, str] = {}
    for i, df in p.frames.items():
        keys = list(p.tree.shared(i))
        if buckets and keys and name:
            tables[i] = f"{name}_{i}"
            df.repartition(buckets, *keys).write.bucketBy(buckets, *keys).sortBy(*keys).option("path", f"{path}/{i}").mode("overwrite").saveAsTable(tables[i])
        else:
            clustered = df.repartition(*keys).sortWithinPartitions(*keys, "_opt") if keys else df.repartitionByRange("_opt").sortWithinPartitions("_opt")
            clustered.write.mode("overwrite").parquet(f"{path}/{i}")
    shape = {"atoms": [[a.name, list(a.variables)] for a in p.tree.query.atoms], "head": list(p.tree.query.head), "order": list(p.tree.order), "parent": list(p.tree.parent)}
    shape |= {"tables": tables, "buckets": buckets, "keys": {i: list(p.tree.shared(i)) for i in tables}}
    spark.createDataFrame([(json.dumps(shape),)], "shape string").coalesce(1).write.mode("overwrite").json(f"{path}/shape")


def load_prepared(spark: SparkSession, path: str, rank: Rank) -> Prepared:
    """Relations as ``save_prepared`` left them. Bucketed ones come back as tables, so that joins and groups by their keys
    need no shuffle; a catalog that doesn't know them any more gets them declared again over the same files."""
    shape = json.loads(spark.read.json(f"{path}/shape").first()["shape"])
    frames = {}
    for i in range(len(shape["atoms"])):
        name = shape["tables"].get(str(i))
        if name is None:
            frames[i] = spark.read.parquet(f"{path}/{i}")
            continue
        if not spark.catalog.tableExists(name):
            columns = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in spark.read.parquet(f"{path}/{i}").schema)
            keys = ", ".join(f"`{k}`" for k in shape["keys"][str(i)])
            spark.sql(f"create table {name} ({columns}) using parquet clustered by ({keys}) sorted by ({keys}) into {shape['buckets']} buckets location '{path}/{i}'")
        frames[i] = spark.table(name)
    atoms = tuple(Atom(name, frames[i].select(*variables), tuple(variables)) for i, (name, variables) in enumerate(shape["atoms"]))
    q = ConjunctiveQuery(atoms, tuple(shape["head"]), tuple(a.name for a in atoms))
    return Prepared(JoinTree(q, tuple(shape["order"]), tuple(shape["parent"])), rank.algebra, rank, frames)


def join_groups(p: Prepared, i: int, by: Sequence[Column], most: int | None = None) -> DataFrame:
    """One row a join group of relation i: its key, its size and its first ``most`` rows (all without) in rank order as an
    array of structs. Groups are meant to be small or cut; ``sort_groups`` has no such limit."""
    df, keys = with_all(p.frames[i], p.tree.shared(i))
    rest = [c for c in df.columns if c not in keys]
    placed = df.withColumn("_pos", F.row_number().over(Window.partitionBy(*keys).orderBy(*by)))
    placed = placed.where(F.col("_pos") <= most) if most is not None else placed
    sizes = df.groupBy(*keys).agg(F.count(F.lit(1)).alias("size"))
    packed = placed.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("_pos", *rest))).alias("rows"))
    return packed.join(sizes, keys).select(*keys, "size", "rows")
