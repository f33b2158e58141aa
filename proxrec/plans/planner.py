"""Choice of the operator's form from the sizes of the data, and small helpers on plans."""

from __future__ import annotations

import tempfile
from dataclasses import dataclass

from pyspark.sql import DataFrame

#: Fixed thresholds of the choice; all are sizes that the driver or an executor holds at once. A rating on the driver takes some 200 bytes.
DENSE_ITEMS, LOCAL_NNZ, BROADCAST_BYTES = 3_000, 2_000_000, 512_000_000
#: Items up to which the driver forms a full matrix of pairs (Jaccard has no product form).
PAIR_ITEMS = 6_000


@dataclass(frozen=True)
class OperatorPlan:
    form: str  # dense, local, blocks or relational
    reason: str
    flops_a_step: float
    bytes_on_driver: float


def choose_operator(n_users: int, n_items: int, nnz: int, f: int = 50, similarity: str = "cosine") -> OperatorPlan:
    """dense: the item matrix is small and cheaper than many passes; local: ratings fit the driver; blocks: vectors fit a broadcast.

    Similarities without a product form go to blocks, where their pairs stay on Spark, once the driver could not hold the matrix.
    """
    dense, local, basis = 8.0 * n_items**2, 24.0 * nnz, 8.0 * n_items * (f + 20)
    if n_items <= DENSE_ITEMS:
        return OperatorPlan("dense", f"{n_items} items: one pass forms the matrix", 2.0 * n_items**2, dense)
    if nnz <= LOCAL_NNZ and (similarity in ("cosine", "pearson") or n_items <= PAIR_ITEMS):
        return OperatorPlan("local", f"{nnz} ratings fit the driver", 4.0 * nnz, local + basis)
    if basis <= BROADCAST_BYTES:
        return OperatorPlan("blocks", f"{basis / 1e6:.0f} MB of vectors are broadcast, rows stay", 4.0 * nnz, 2 * basis)
    return OperatorPlan("relational", "vectors exceed a broadcast", 4.0 * nnz, 0.0)


def cost_model(n_users: int, n_items: int, nnz: int, f: int, steps: int) -> dict[str, float]:
    """Flops and bytes of a solve: products steps * nnz, orthogonalisation steps^2 * items, basis steps * items."""
    return {
        "product_flops": 4.0 * steps * nnz,
        "orthogonalisation_flops": 2.0 * steps * (steps + 1) * n_items,
        "basis_bytes": 8.0 * steps * n_items,
        "recommend_flops": 2.0 * f * (nnz + float(n_users) * n_items),
    }


def cut(df: DataFrame) -> DataFrame:
    """Materialises df in the cluster's checkpoint folder; where none is named, a local session gets a temporary one and a cluster an error."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        folder = df.sparkSession.conf.get("spark.checkpoint.dir", None)
        if folder is None and not sc.master.startswith("local"):
            raise ValueError("name a folder that all executors share in spark.checkpoint.dir")
        sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="proxrec-"))
    return df.checkpoint(eager=True)
