"""How a join is run."""

from __future__ import annotations

from dataclasses import dataclass

SAMPLERS = ("random", "stratified", "local", "distribution_aware", "generative")
SPLITTERS = ("iterative", "learned", "widest")
#: Regions that a first split makes unless more are asked for.
MOST_REGIONS = 1024


@dataclass(frozen=True)
class JoinConfig:
    """Parameters of the join; None is chosen from the number of objects.

    sampler, oversample: where pivots come from, and how many times k of them.
    k pivots, p regions, n axes of the target space.
    node_by, nodes: strata of the data: 'hash', 'range', 'partition' or a column.
    axes: 'random' pivots, or each 'farthest' from those before.
    families, model, cells, gof_rows, c_min: fits and their test; cells_by: cells of equal 'probability' or 'width'.
    boxes: slices that real pivots are drawn from, 'equal_probability' or 'equal_width'.
    space: where fits and pivots live, 'origin' (vectors) or 'target' (any metric); snap: replace a
    generated pivot by the nearest of as many real ones.
    n_labels, label_space: clusters of pivots for the learned split.
    bounds: 'data_box' and 'cell' are exact, 'pivot_box' loses pairs and is kept for measuring that.
    replication: copies go to 'lower' regions than home, or to 'both' sides as published.
    engine: 'block' (numpy, vectors) or 'sql'. max_region: rows of a region in one task; larger
    ones are dealt into a grid. filters: length, prefix and position filters inside regions; segments:
    that of segments too, for strings. collapse: compare equal objects once.
    max_copies: a plan that expects more rows per object than this uses fewer regions; None takes it as it is.
    per_region: regions of more objects are split again by a sample of their own; None leaves them.
    """

    sampler: str = "generative"
    splitter: str = "learned"
    oversample: int = 1
    k: int | None = None
    p: int | None = None
    n: int | None = None
    node_by: str = "hash"
    nodes: int = 4
    axes: str = "random"
    families: tuple[str, ...] = ("normal", "exponential", "gamma")
    cells_by: str = "probability"
    boxes: str = "equal_probability"
    model: str = "marginal"
    cells: int | None = None
    gof_rows: int = 10_000
    c_min: float = 1e-3
    space: str | None = None
    snap: bool = False
    n_labels: int | None = None
    label_space: str | None = None
    bounds: str = "data_box"
    replication: str = "lower"
    engine: str | None = None
    filters: bool = True
    segments: bool = False
    collapse: bool = False
    max_region: int = 20_000
    max_copies: float | None = 4.0
    per_region: int | None = 200_000
    seed: int = 7

    def sized(self, rows: int) -> tuple[int, int, int]:
        """k, p, n for so many objects: the published defaults, shrunk on small inputs, and p grown with the data up to MOST_REGIONS.

        What comes to the driver is so bounded; beyond, regions are split again (per_region) and dealt into blocks (max_region).
        """
        p = self.p or max(1, min(max(60, rows // 50_000), MOST_REGIONS, rows // 50 or 1))
        k = self.k or min(max(3200, 8 * p), max(4 * p, rows // 4, 1))
        n = self.n or min(10, max(1, k))
        return min(k, max(rows, 1)), p, n
