"""Rules that choose the shape of a search or a de-duplication before Catalyst sees it, each of which can be turned
off."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, functions as F

from nearcopy.operators.index import VectorIndex


@dataclass
class Plan:
    steps: list[str] = field(default_factory=list)
    nprobe: int = 1
    salt: int = 1
    collapse: bool = False
    ball: bool = False

    def explain(self) -> str:
        return "\n".join(f"{'  ' * i}+- {s}" for i, s in enumerate(self.steps))


def cell_sizes(index: VectorIndex) -> DataFrame:
    return index.encoded.groupBy("cell").count()


def plan_search(
    index: VectorIndex, queries: int, nprobe: int, k: int, rows_per_task: int = 1_000_000, off: tuple[str, ...] = ()
) -> Plan:
    """Rules: probe (no more cells than there are), salt (a hot cell's rows over several tasks), push (the upper
    bound below the k nearest)."""
    p = Plan(nprobe=nprobe)
    cells = len(index.cells) if index.cells is not None else 1
    if "probe" not in off and nprobe > cells:
        p.nprobe = cells
        p.steps.append(f"probe: {nprobe} cells asked for, {cells} exist")
    if "salt" not in off:
        most = cell_sizes(index).agg(F.max("count")).first()[0] or 0
        p.salt = max(1, -(-most // rows_per_task))
        p.steps.append(f"salt: the largest list has {most} rows, {p.salt} task(s) each")
    p.steps.append(f"search: {queries} queries, {p.nprobe} cells, {k} nearest")
    return p


def plan_dedup(index: VectorIndex, k: int, tol: float, off: tuple[str, ...] = ()) -> Plan:
    """Rules: collapse (rows of equal code are searched once, when some group exceeds k), ball (all within the bound
    instead of k, when groups exceed k)."""
    p = Plan()
    most = index.encoded.groupBy("cell", "codes").count().agg(F.max("count")).first()[0] or 0
    if "collapse" not in off and most > k:
        p.collapse = True
        p.steps.append(f"collapse: {most} rows share a code, more than k = {k}")
    if "ball" not in off and most > k:
        p.ball = True
        p.steps.append(f"ball: all rows within {1 + tol:g} times the self-distance")
    p.steps.append("flag, parent, pointer jump")
    return p


def cell_radii(index: VectorIndex) -> np.ndarray:
    """Largest distance of a cell's reconstructions to its centroid."""
    from nearcopy.functions import linalg as L

    y = index.decode(index.encoded).join(index.encoded.select("id", "cell"), "id")
    centroids = index.encoded.sparkSession.createDataFrame(
        [(i, c.tolist()) for i, c in enumerate(index.cells)], "cell int, c array<double>"
    )
    out = np.zeros(len(index.cells))
    for r in y.join(F.broadcast(centroids), "cell").groupBy("cell").agg(F.max(L.l2(F.col("y"), F.col("c"))).alias("r")).collect():  # one row a cell
        out[r["cell"]] = r["r"]
    return out


def prune_probes(probes: DataFrame, index: VectorIndex, tol: float, radii: np.ndarray) -> DataFrame:
    """Drop (query, cell) whose ball can't reach any code of the cell: |x - c| - radius > (1 + tol) * self-distance.
    Exact for the ball search."""
    from nearcopy.functions import linalg as L

    rows = [(i, c.tolist(), float(r)) for i, (c, r) in enumerate(zip(index.cells, radii, strict=True))]
    cells = probes.sparkSession.createDataFrame(rows, "cell int, c array<double>, radius double")
    kept = probes.join(F.broadcast(cells), "cell").where(
        L.l2(F.col("z"), F.col("c")) - F.col("radius") <= (1 + tol) * F.col("self_dist") + 1e-9
    )
    return kept.drop("c", "radius")
