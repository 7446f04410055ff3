"""NumPy kernels that run inside one task."""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from farpoint.functions.distance import Metric, metric

#: Rows that one center is compared with at a time.
BLOCK = 8192
#: Tiles of a distance table, and the number of centers from which tables are made.
ROWS, COLUMNS, PRODUCTS = 1024, 256, 16
#: Points and centers of a box, boxes looked at in one step, and where boxes are used: so many centers, at most so many dimensions.
POINTS_IN_BOX, CENTERS_IN_BOX, BOXES, BOXED, BOXED_DIMENSIONS = 256, 64, 4, 512, 8


def matrix(column: pa.Array) -> np.ndarray:
    """A list column of equal lengths as (rows, dimensions)."""
    values = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64, copy=False)
    return values.reshape(len(column), -1) if len(column) else np.empty((0, 0))


def by_id(ids: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(ids, kind="stable")
    return ids[order], x[order]


def farthest_first(x: np.ndarray, k: int, seed: int = 0, target: float = 0.0, measure: str | Metric = "euclidean", start: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, float]:
    """Rows of the chosen points, the key at which each was chosen, and the key of the radius.

    Rows are taken to be sorted by id: of several farthest points argmax takes the first. Stops
    early when the farthest key is not above ``target`` (0: all points are covered exactly).
    ``start`` holds keys to centers chosen before; then the first pick is the farthest point too.
    """
    m = metric(measure)
    if not len(x) or k < 1:
        return np.empty(0, np.int64), np.empty(0), 0.0
    picks, keys = [], []
    if start is None:
        picks, keys, low = [seed], [np.inf], m.kernel(x, x[seed])
    else:
        low = start.copy()
    while len(picks) < k:
        far = int(np.argmax(low))
        if low[far] <= target:
            break
        picks.append(far)
        keys.append(float(low[far]))
        np.minimum(low, m.kernel(x, x[far]), out=low)
    return np.array(picks), np.array(keys), float(low.max())


def farthest_first_pruned(x: np.ndarray, k: int, seed: int = 0) -> tuple[np.ndarray, np.ndarray, float]:
    """The same picks for the Euclidean metric with fewer distances.

    By the triangle inequality a new center at least twice as far from an old one as the old
    one's farthest point cannot take over any of its points, so those clusters are passed over.
    """
    m = metric("euclidean")
    owner, low = np.zeros(len(x), np.int64), m.kernel(x, x[seed])
    picks, keys = [seed], [np.inf]
    while len(picks) < min(k, len(x)):
        far = int(np.argmax(low))
        key = float(low[far])
        if key <= 0:
            break
        reach = np.zeros(len(picks))
        np.maximum.at(reach, owner, low)
        gaps = m.kernel(x[picks], x[far])
        near = gaps < 4 * reach * (1 + 1e-12)
        todo = np.flatnonzero(near[owner])
        d = m.kernel(x[todo], x[far])
        better = d < low[todo]
        low[todo[better]], owner[todo[better]] = d[better], len(picks)
        picks.append(far)
        keys.append(key)
    return np.array(picks), np.array(keys), float(low.max())


def products_are_exact(x: np.ndarray, centers: np.ndarray) -> bool:
    """Whole coordinates so small that all sums of products stay below 2**53."""
    if not (len(x) and len(centers)) or not ((x == np.rint(x)).all() and (centers == np.rint(centers)).all()):
        return False
    most = max(np.abs(x).max(), np.abs(centers).max())
    return 4 * x.shape[1] * most * most < 2**53


def nearest(x: np.ndarray, centers: np.ndarray, measure: str | Metric = "euclidean") -> tuple[np.ndarray, np.ndarray]:
    """For each row the index of its nearest center (the first of equals) and the key."""
    m = metric(measure)
    if m.name == "euclidean" and len(centers) >= PRODUCTS and products_are_exact(x, centers):
        return nearest_product(x, centers)
    best, which = np.full(len(x), np.inf), np.zeros(len(x), np.int64)
    for lo in range(0, len(x), BLOCK):
        block = x[lo : lo + BLOCK]
        for j, c in enumerate(centers):
            d = m.kernel(block, c)
            closer = d < best[lo : lo + BLOCK]
            best[lo : lo + BLOCK][closer] = d[closer]
            which[lo : lo + BLOCK][closer] = j
    return which, best


def _tiles(x: np.ndarray, centers: np.ndarray):
    """(first row, first center, -2 x.c + c.c) in tiles that stay in the cache, and the rows' own squares."""
    wide = np.column_stack([-2.0 * centers, (centers * centers).sum(1)]).T.copy()
    tall = np.column_stack([x, np.ones(len(x))])
    for lo in range(0, len(x), ROWS):
        for at in range(0, len(centers), COLUMNS):
            yield lo, at, tall[lo : lo + ROWS] @ wide[:, at : at + COLUMNS]


def nearest_product(x: np.ndarray, centers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """nearest() for squared Euclidean keys through matrix products; exact where products_are_exact."""
    best, which = np.full(len(x), np.inf), np.zeros(len(x), np.int64)
    for lo, at, d in _tiles(x, centers):
        arg = d.argmin(1)
        low = d[np.arange(len(d)), arg]
        closer = low < best[lo : lo + ROWS]
        best[lo : lo + ROWS][closer] = low[closer]
        which[lo : lo + ROWS][closer] = arg[closer] + at
    return which, best + (x * x).sum(1)


def lower_keys(x: np.ndarray, low: np.ndarray, centers: np.ndarray, measure: str | Metric = "euclidean") -> np.ndarray:
    """min(low, keys to the nearest of ``centers``)."""
    m = metric(measure)
    if m.name == "euclidean" and len(centers) >= PRODUCTS:
        if products_are_exact(x, centers):
            best = np.full(len(x), np.inf)
            for lo, _, d in _tiles(x, centers):
                part = best[lo : lo + ROWS]
                np.minimum(part, d.min(1), out=part)
            return np.minimum(low, best + (x * x).sum(1))
        out = low.copy()
        for lo in range(0, len(x), ROWS):
            block, part = x[lo : lo + ROWS], out[lo : lo + ROWS]
            for at in range(0, len(centers), COLUMNS):
                tile = np.zeros((len(block), min(COLUMNS, len(centers) - at)))
                for j in range(x.shape[1]):
                    d = block[:, j, None] - centers[None, at : at + COLUMNS, j]
                    d *= d
                    tile += d
                np.minimum(part, tile.min(1), out=part)
        return out
    out = low.copy()
    for lo in range(0, len(x), BLOCK):
        block, part = x[lo : lo + BLOCK], out[lo : lo + BLOCK]
        for c in centers:
            np.minimum(part, m.kernel(block, c), out=part)
    return out


def halved(x: np.ndarray, most: int) -> list[np.ndarray]:
    """Rows of boxes with ``most`` points at most, by halving the widest side."""
    out, todo = [], [np.arange(len(x))]
    while todo:
        rows = todo.pop()
        if len(rows) <= most:
            out.append(rows)
            continue
        part = x[rows]
        half = len(rows) // 2
        rows = rows[np.argpartition(part[:, int(np.argmax(part.max(0) - part.min(0)))], half)]
        todo += [rows[:half], rows[half:]]
    return out


def boxed(centers: np.ndarray, measure: str | Metric = "euclidean") -> bool:
    """Whether Boxes are worth making: many centers in few dimensions."""
    return metric(measure).name == "euclidean" and len(centers) >= BOXED and centers.shape[1] <= BOXED_DIMENSIONS


class Boxes:
    """Many centers in boxes, so that a box of points is compared with near ones only: lower_keys() with fewer distances."""

    def __init__(self, centers: np.ndarray):
        rows = [np.resize(r, CENTERS_IN_BOX) for r in halved(centers, CENTERS_IN_BOX) if len(r)]  # a box repeats centers to be full
        self.centers = centers
        self.tiles = centers[np.array(rows)]
        self.lows, self.highs = self.tiles.min(1), self.tiles.max(1)
        self.wide = np.concatenate([-2.0 * self.tiles, (self.tiles * self.tiles).sum(2)[:, :, None]], axis=2)

    def _keys(self, points: np.ndarray, which: np.ndarray, exact: bool) -> np.ndarray:
        """The key to the nearest center of some boxes."""
        if exact:
            wide = self.wide[which].reshape(-1, points.shape[1] + 1)
            return (np.column_stack([points, np.ones(len(points))]) @ wide.T).min(1) + (points * points).sum(1)
        near = self.tiles[which].reshape(-1, points.shape[1])
        out = np.zeros((len(points), len(near)))
        for j in range(points.shape[1]):
            d = points[:, j, None] - near[None, :, j]
            d *= d
            out += d
        return out.min(1)

    def lower(self, x: np.ndarray, low: np.ndarray) -> np.ndarray:
        """min(low, keys to the nearest center)."""
        out, exact = low.copy(), products_are_exact(x, self.centers)
        for rows in halved(x, POINTS_IN_BOX) if len(x) else []:
            points, part = x[rows], out[rows]
            gap = np.maximum(0.0, np.maximum(self.lows - points.max(0), points.min(0) - self.highs))
            least = (gap * gap).sum(1) * (1 - 1e-9)
            order = np.argsort(least, kind="stable")
            least = least[order]
            at, end = 0, np.searchsorted(least, part.max())
            while at < end:
                part = np.minimum(part, self._keys(points, order[at : min(at + BOXES, end)], exact))
                at, end = at + BOXES, np.searchsorted(least, part.max())
            out[rows] = part
        return out
