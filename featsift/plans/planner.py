"""Choice of the counting strategy and of where the criterion's state lives."""

from __future__ import annotations

from dataclasses import dataclass

from .dataset import Dataset, SparseDataset

#: State sizes up to which it may live on the driver; columns up to which one explode of all candidates compiles well.
DRIVER_STATE, CODEGEN_COLUMNS = 1_000_000, 500


@dataclass(frozen=True)
class Strategy:
    counting: str  # packed, explode, arrow, gsets, blocks or sparse
    state: str  # driver or frame


def choose(ds: Dataset | SparseDataset, state: str = "auto") -> Strategy:
    """Packed blocks while the state fits the driver: of the strategies measured by the bench the fastest at every width.

    With the state in a table, cells are joined to it as they come: sparse ones from packed rows, dense ones by explode
    while one row's candidates compile into one stage, by the Arrow kernel for more columns.
    """
    n = ds.size if ds.sparse else len(ds.features)
    where = state if state != "auto" else "driver" if n <= DRIVER_STATE else "frame"
    if where == "driver":
        return Strategy("packed", where)
    return Strategy("packed" if ds.sparse else "explode" if n <= CODEGEN_COLUMNS else "arrow", where)
