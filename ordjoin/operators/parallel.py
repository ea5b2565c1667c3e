"""Sequential enumerators on many keys at once: one group of rows a key, each enumerated in its own task."""

from __future__ import annotations

from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ordjoin.operators.sequential import SumHeap, local_groups
from ordjoin.plans.jointree import JoinTree, join_tree
from ordjoin.plans.model import Atom, ConjunctiveQuery
from ordjoin.plans.ranking import Rank, assign_weights

MAX_GROUP_ROWS = 1_000_000


def with_optima(tree: JoinTree, frames: dict[int, list[dict]]) -> dict[int, list[dict]]:
    """Rows with a completion below them, with ``_opt`` (min-plus over plain rows)."""
    best: dict[int, dict[tuple, object]] = {}
    out: dict[int, list[dict]] = {}
    for i in reversed(tree.order):
        rows = []
        for r in frames.get(i, []):
            below = [best[c].get(tuple(r[v] for v in tree.shared(c))) for c in tree.children(i)]
            if None not in below:
                rows.append({**r, "_opt": r["_w"] + sum(below)})
        out[i] = rows
        table: dict[tuple, object] = {}
        for r in rows:
            k = tuple(r[v] for v in tree.shared(i))
            table[k] = min(table.get(k, r["_opt"]), r["_opt"])
        best[i] = table
    return out


def per_key_topk(q: ConjunctiveQuery, rank: Rank, key: str, k: int) -> DataFrame:
    """The k best answers for each value of a variable that stands in every atom (SUM of integers), with ``rnk``.

    A key's rows must fit one task (refused beyond MAX_GROUP_ROWS); ``levels.per_group_topk`` has no such limit.
    """
    if any(key not in a.variables for a in q.atoms):
        raise ValueError(f"{key} isn't in every atom")
    tree = join_tree(q)
    weights = assign_weights(rank, tree)
    kinds = {v: t for a in q.atoms for v, t in a.frame.dtypes}
    parts = []
    for i, a in enumerate(q.atoms):
        columns = [(F.col(v) if v in a.variables else F.lit(None).cast(kinds[v])).alias(v) for v in q.variables]
        parts.append(a.frame.withColumn("_w", weights[i].cast("long")).select(F.lit(i).alias("_atom"), *columns, "_w"))
    rows = reduce(DataFrame.unionByName, parts)
    bare = ConjunctiveQuery(tuple(Atom(a.name, None, a.variables) for a in q.atoms), q.head, q.relations)
    shape = JoinTree(bare, tree.order, tree.parent)
    head, variables = list(q.head), {i: a.variables for i, a in enumerate(q.atoms)}

    def each(group: pd.DataFrame) -> pd.DataFrame:
        if len(group) > MAX_GROUP_ROWS:
            raise MemoryError("a key has too many rows for one task")
        frames = {i: part[[*variables[int(i)], "_w"]].to_dict("records") for i, part in group.groupby("_atom")}
        found = []
        for n, (w, a) in enumerate(SumHeap(local_groups(shape, with_optima(shape, frames), by_optimum=True)), 1):
            found.append({**a, "weight": int(w), "rnk": n})
            if n == k:
                break
        return pd.DataFrame(found, columns=[*head, "weight", "rnk"])

    schema = ", ".join(f"`{v}` {kinds[v]}" for v in head) + ", weight long, rnk long"
    out = rows.groupBy(key).applyInPandas(each, schema)
    return out.withColumn("weight", rank.decode(F.col("weight")))
