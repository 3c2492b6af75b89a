"""Small planner for the engine's own steps; returns names, builds nothing."""

from __future__ import annotations

from ..functions import metrics

MODEL_BYTES = 256 << 20
DENSE_POINTS = 3_000
LOCAL_POINTS = 60_000
SCAN_POINTS = 1_000_000  # points, not pairs, that a fit by scans holds
LOCAL_EDGES = 40_000_000


def choose_pair_strategy(dims: int | None, metric: str, size: int) -> str:
    """Exact strategies only: cells for few Euclidean dimensions, tiles for small tables, pivots for other metrics."""
    m = metrics.get(metric)
    if metric == "euclidean" and dims is not None and dims <= 4:
        return "grid"
    if not m.is_metric or size < 32 << 20:
        return "tile"
    return "pivot"


def choose_solver(n: int, edges: int) -> str:
    if n <= DENSE_POINTS:
        return "dense"
    return "lanczos" if n <= LOCAL_POINTS and edges <= LOCAL_EDGES else "distributed"


def choose_extension(rows: int, width: int, modes: int) -> str:
    """A model is shipped to the tasks while it fits; beyond that its blocks are joined."""
    return "ship" if rows * (width + modes + 2) * 8 <= MODEL_BYTES else "tiles"


def explain(points: int, dims: int, metric: str, landmarks: int, modes: int) -> str:
    size = points * dims * 8
    return f"pairs: {choose_pair_strategy(dims, metric, size)}; fit: {choose_solver(landmarks, landmarks * landmarks // 2)}; extend: {choose_extension(landmarks, dims, modes)}"
