"""What distributed discovery is compared with: local discovery, samples, a single task, brute force on the driver; and how exact they are."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame

from depmine.functions.bits import antichain, names, subset
from depmine.operators import compare, cover, partition

from . import lattice, planner
from .result import FD, Meter


def local_fds(table: pa.Table, max_lhs: int | None) -> list[tuple[int, int]]:
    """The level-wise search on one node's rows."""
    codes = partition.encode(table)
    return lattice.run_fd(lambda masks: {x: partition.count_distinct(codes, x) for x in masks}, table.num_columns, table.num_rows, max_lhs, Meter())


def local_intersect(df: DataFrame, node, k: int, max_lhs: int | None) -> list[tuple[int, int]]:
    """Every node finds the dependencies of its own rows; those that hold on all nodes are reported, minimal ones only. node: a column of node numbers."""
    attrs = df.columns

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        found = local_fds(pa.Table.from_pandas(pdf[attrs], preserve_index=False), max_lhs)
        return pd.DataFrame([(str(x), str(a)) for x, a in found], columns=["lhs", "rhs"]).assign(node=int(pdf["_node"].iloc[0]))

    rows = df.withColumn("_node", node.cast("int")).groupBy("_node").applyInPandas(run, "lhs string, rhs string, node int").collect()
    by_node: dict[int, dict[int, list[int]]] = {}
    for r in rows:
        by_node.setdefault(r["node"], {}).setdefault(int(r["rhs"]), []).append(int(r["lhs"]))
    out = []
    for i in range(len(attrs)):
        bit = 1 << i
        lists = [n.get(bit, []) for n in by_node.values()]
        joint = lists[0] if lists else []
        for other in lists[1:]:  # a set holds on both iff it contains a minimal one of each
            joint = minimal_unions(joint, other, max_lhs)
        out += [(x, bit) for x in joint]
    return out


def minimal_unions(a: list[int], b: list[int], max_lhs: int | None) -> list[int]:
    return antichain(x | y for x in a for y in b if max_lhs is None or (x | y).bit_count() <= max_lhs)


def sample_only(df: DataFrame, keep, max_lhs: int | None) -> list[tuple[int, int]]:
    """Discovery on a sample alone, as on any relation. keep: a deterministic condition."""
    return planner.whole(df.where(keep), memory="resident", max_lhs=max_lhs).found


def single_task(df: DataFrame, method: str = "lattice", max_lhs: int | None = None) -> DataFrame:
    """The undistributed algorithm: the whole relation in one Python task, by design."""
    attrs = df.columns

    def run(batches):
        held = list(batches)
        whole = pa.Table.from_batches(held) if held else None
        if whole is None:
            found = [(0, 1 << a) for a in range(len(attrs))]
        elif method == "lattice":
            found = local_fds(whole, max_lhs)
        else:
            form = compare.Form(attrs)
            seen = set(compare.all_pairs(whole, form)) - {0} if form.bits <= 62 else differing([c for c, _ in partition.encode(whole)])
            found = [(x, 1 << a) for a in range(len(attrs)) for x in cover.of_rhs(seen, 1 << a, max_lhs)]
        rows = [(names(x, attrs), names(a, attrs), x.bit_count()) for x, a in found]
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.string(), pa.string(), pa.int32()))], ["lhs", "rhs", "lhs_size"])

    return df.coalesce(1).mapInArrow(run, FD)


def differing(codes: list[np.ndarray]) -> set[int]:
    """The masks of differing attributes of all pairs of rows, each row against those before it."""
    seen: set[int] = set()
    for i in range(1, len(codes[0])):
        words = []
        for at in range(0, len(codes), 62):
            word = np.zeros(i, np.int64)
            for j, c in enumerate(codes[at : at + 62]):
                word |= (c[:i] != c[i]).astype(np.int64) << j
            words.append(word)
        if len(words) == 1:
            seen.update(np.unique(words[0]).tolist())
        else:
            seen.update(sum(int(w) << 62 * n for n, w in enumerate(row)) for row in np.unique(np.stack(words, axis=1), axis=0).tolist())
    return seen - {0}


def holds(lhs: int, rhs: int, fds) -> bool:
    return any(a == rhs and subset(x, lhs) for x, a in fds)


def precision(local, exact) -> tuple[float, float]:
    """Share of reported dependencies that hold on the whole, and of all true ones that are implied by the reported ones."""
    right = sum(holds(x, a, exact) for x, a in local)
    return (right / len(local) if local else 1.0), (sum(holds(x, a, local) for x, a in exact) / len(exact) if exact else 1.0)
