"""Distance expressions for Catalyst and block kernels for Arrow batches."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def sq_dist(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def priority(seed: int, key: Column) -> Column:
    """Repeatable random order, equal in every engine: md5 of seed and key."""
    return F.md5(F.concat(F.lit(f"{seed}:"), key.cast("string")).cast("binary"))


def uniform(seed: int, key: Column) -> Column:
    """The priority's first 32 bits as a number in [0, 1)."""
    return F.conv(F.substring(priority(seed, key), 1, 8), 16, 10).cast("double") / F.lit(float(1 << 32))


def to_matrix(series) -> np.ndarray:
    return np.stack([np.asarray(x, np.float64) for x in series]) if len(series) else np.zeros((0, 1))


def collect_matrix(df: DataFrame, col: str) -> tuple[pa.Table, np.ndarray]:
    """The rows of a bounded table and its vectors of equal length as a matrix, by way of Arrow: 8 bytes a number on
    the driver, where rows of Python floats take about five times as much."""
    rows = df.toArrow()
    if not rows.num_rows:
        return rows, np.zeros((0, 1))
    out, at = None, 0
    for chunk in rows.column(col).chunks:  # one copy, batch by batch
        x = list_matrix(chunk)
        if len(x):
            out = np.empty((rows.num_rows, x.shape[1])) if out is None else out
            out[at : at + len(x)] = x
            at += len(x)
    return rows.drop_columns([col]), out


def list_matrix(column: pa.Array) -> np.ndarray:
    """Rows of an Arrow column of lists of equal length, without a Python object for each."""
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64, copy=False)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 1))


def matrix_frame(spark: SparkSession, ids: dict[str, np.ndarray], name: str, matrix: np.ndarray) -> DataFrame:
    """Long columns and a vector column, by way of Arrow."""
    if not len(matrix):
        return spark.createDataFrame([], ", ".join([f"{c} long" for c in ids] + [f"{name} array<double>"]))
    ends = pa.array(np.arange(len(matrix) + 1, dtype=np.int32) * matrix.shape[1])
    vecs = pa.ListArray.from_arrays(ends, pa.array(np.ascontiguousarray(matrix, np.float64).ravel()))
    cols = {c: pa.array(np.asarray(v, np.int64)) for c, v in ids.items()}
    return spark.createDataFrame(pa.table(cols | {name: vecs}))


def long_frame(spark: SparkSession, cols: dict[str, np.ndarray]) -> DataFrame:
    """Long columns, by way of Arrow."""
    if not len(next(iter(cols.values()))):
        return spark.createDataFrame([], ", ".join(f"{c} long" for c in cols))
    return spark.createDataFrame(pa.table({c: pa.array(np.asarray(v, np.int64)) for c, v in cols.items()}))


SCREENED = 2048  # centroids from which distances are taken in single precision first


class Screen:
    """nearest() for many centroids, made once for all points. Centroids are halved along their main directions into
    tiles of at most `wide`. A point meets the tiles that are not ruled out by their box or ball against the best it
    has found, in single precision; tiles whose least distance is the least of all or within the rounding error of it
    are compared in double precision, so the answer is that of double precision."""

    def __init__(self, centroids: np.ndarray, wide: int = 320, axes: int = 5):
        self.middle = centroids.mean(axis=0)
        moved = centroids - self.middle
        size = (moved**2).sum(axis=1)
        self.reach = float(np.sqrt(size.max(initial=0.0)))
        self.usable = 1e-12 < self.reach < 1e15  # or the error bounds do not hold
        if not self.usable:
            return
        self.axes = np.linalg.eigh(moved.T @ moved)[1][:, ::-1][:, :axes]
        along = moved @ self.axes
        self.tiles, todo = [], [np.arange(len(moved))]
        while todo:
            ids = todo.pop()
            if len(ids) <= wide:
                self.tiles.append(np.sort(ids))  # equal distances go to the lower index
                continue
            turn = along[ids, along[ids].var(axis=0).argmax()]
            order = ids[np.argsort(turn, kind="stable")]
            todo += [order[len(order) // 2 :], order[: len(order) // 2]]
        self.centroids = centroids
        self.moved, self.size = [moved[t].T for t in self.tiles], [size[t] for t in self.tiles]
        self.single = [np.hstack([-2 * moved[t], size[t, None]]).astype(np.float32) for t in self.tiles]
        self.least, self.most = (np.array([f(along[t], axis=0) for t in self.tiles]).T for f in (np.min, np.max))
        self.centre = np.array([moved[t].mean(axis=0) for t in self.tiles])
        self.centre_size = (self.centre**2).sum(axis=1)
        self.radius = np.array([np.sqrt(((moved[t] - c) ** 2).sum(axis=1).max()) for t, c in zip(self.tiles, self.centre)])

    def _bounds(self, y: np.ndarray, far: np.ndarray, slack: np.ndarray, rows: int = 256) -> tuple[np.ndarray, np.ndarray]:
        """(tile x point: least that size - 2 y c can be for the tile's centroids, point x 2: tiles of the nearest centres)."""
        bound, homes = np.empty((len(self.tiles), len(y)), np.float32), np.zeros((len(y), 2), np.int64)
        for i in range(0, len(y), rows):  # blocks that stay in a core's cache
            part, off = y[i : i + rows], far[i : i + rows]
            ball = -2 * (self.centre @ part.T)
            ball += self.centre_size[:, None]
            ball += off**2
            homes[i : i + rows, 0] = ball.argmin(axis=0)
            homes[i : i + rows, 1] = np.argpartition(ball, min(1, len(ball) - 1), axis=0)[:2].max(axis=0) if len(ball) > 1 else 0
            np.sqrt(np.maximum(ball, 0, out=ball), out=ball)
            ball -= (self.radius[:, None] + 4e-7 * (off + self.reach))  # roundings of the square root's argument
            np.maximum(ball, 0, out=ball)
            ball *= ball
            box, at, gap, other = np.zeros_like(ball), self.axes.T @ part.T, np.empty_like(ball), np.empty_like(ball)
            for here, low, high in zip(at, self.least, self.most):
                np.subtract(low[:, None], here, out=gap)
                np.subtract(here, high[:, None], out=other)
                np.maximum(gap, other, out=gap)
                np.maximum(gap, 0, out=gap)
                gap *= gap
                box += gap
            np.maximum(ball, box, out=box)
            box -= off**2 + 2 * slack[i : i + rows] + 1e-6 * (off + self.reach) ** 2  # roundings, single precision too
            bound[:, i : i + rows] = box
        return bound, homes

    def nearest(self, points: np.ndarray, block: int) -> tuple[np.ndarray, np.ndarray] | None:
        """None where numbers are too large or small for the error bounds."""
        if not self.usable or not len(points):
            return None
        at, best = np.zeros(len(points), np.int64), np.zeros(len(points))
        widest = max(len(t) for t in self.tiles)
        buffer = np.empty(widest * min(512, block), np.float32)
        for i in range(0, len(points), block):
            x = points[i : i + block]
            y = x - self.middle
            far = np.sqrt((y**2).sum(axis=1))
            if not far.max() < 1e15:  # NaN too
                return None
            # 2 x (terms + 5) roundings of a sum of terms whose sizes add up to at most this
            slack = 2 * (x.shape[1] + 5) * 2.0**-24 * (2 * far * self.reach + self.reach**2)
            z = np.hstack([y, np.ones((len(y), 1))]).astype(np.float32)
            bound, homes = self._bounds(y, far, slack)
            least = np.full((len(self.tiles), len(x)), np.inf, np.float32)
            found = np.full(len(x), np.inf, np.float32)

            def visit(t: int, rows: np.ndarray) -> None:
                tile = self.single[t]
                for a in range(0, len(rows), 512):
                    some = rows[a : a + 512]
                    d = np.matmul(tile, z[some].T, out=buffer[: len(tile) * len(some)].reshape(len(tile), -1)).min(axis=0)
                    least[t, some] = d
                    found[some] = np.minimum(found[some], d)

            for home in homes.T:
                order = np.argsort(home, kind="stable")
                for rows in np.split(order, np.flatnonzero(np.diff(home[order])) + 1):
                    visit(home[rows[0]], rows)
                    bound[home[rows[0]], rows] = np.inf  # not again
            for t in range(len(self.tiles)):
                rows = np.flatnonzero(bound[t] <= found)
                if len(rows):
                    visit(t, rows)
            near = least <= found + slack
            low, node = np.full(len(x), np.inf), np.zeros(len(x), np.int64)
            for t, ids in enumerate(self.tiles):
                rows = np.flatnonzero(near[t])
                if len(rows):
                    d = self.size[t] - 2 * (y[rows] @ self.moved[t])
                    of, here = np.nonzero(d <= (d.min(axis=1) + slack[rows] * 2.0**-28)[:, None])  # equal but for roundings
                    here = ids[here]
                    d = ((x[rows[of]] - self.centroids[here]) ** 2).sum(axis=1)
                    if len(of) > len(rows):
                        order = np.lexsort((here, d, of))
                        order = order[np.flatnonzero(np.diff(of[order], prepend=-1))]
                        d, here = d[order], here[order]
                    nearer = (d < low[rows]) | ((d == low[rows]) & (here < node[rows]))
                    low[rows[nearer]], node[rows[nearer]] = d[nearer], here[nearer]
            at[i : i + block], best[i : i + block] = node, low
        return at, best


def _screened(points: np.ndarray, centroids: np.ndarray, block: int) -> tuple[np.ndarray, np.ndarray] | None:
    """Once, for centroids that are not met again."""
    return Screen(centroids).nearest(points, block)


def screen(centroids: np.ndarray) -> Screen | None:
    """What nearest() needs to know of many centroids; None for few."""
    return Screen(centroids) if len(centroids) >= SCREENED else None


def nearest(
    points: np.ndarray, centroids: np.ndarray, block: int = 8192, most: int = 1 << 22, known: Screen | None = None
) -> tuple[np.ndarray, np.ndarray]:
    """(index of the nearest centroid, squared distance); equal distances go to the lower index. Distances are held
    for at most `most` pairs at a time, whatever the number of centroids. known: screen() of the centroids, for callers
    with many batches of points."""
    known = known or screen(centroids)
    if known and (found := known.nearest(points, max(64, min(8192, block, most // 256)))) is not None:
        return found
    at, best = np.zeros(len(points), np.int64), np.zeros(len(points))
    size = (centroids**2).sum(axis=1)
    wide = max(1, min(len(centroids), 2048, most // 64))  # tiles of pairs that stay in a core's cache
    block = max(64, min(block, 512, most // wide)) if len(centroids) > 2048 else max(64, min(block, most // wide))
    turned = np.ascontiguousarray(-2 * centroids.T)
    for i in range(0, len(points), block):
        x = points[i : i + block]
        low, found = np.full(len(x), np.inf), np.zeros(len(x), np.int64)
        for j in range(0, len(centroids), wide):
            d = x @ turned[:, j : j + wide]
            d += size[None, j : j + wide]
            here = d.argmin(axis=1)
            d = d[np.arange(len(x)), here]
            nearer = d < low
            low[nearer], found[nearer] = d[nearer], here[nearer] + j
        at[i : i + block] = found
        best[i : i + block] = ((x - centroids[found]) ** 2).sum(axis=1)
    return at, best


def plusplus(points: np.ndarray, k: int, rng: np.random.Generator, weights: np.ndarray | None = None) -> np.ndarray:
    """D-squared seeding: each next seed drawn in proportion to its distance from those chosen."""
    w = np.ones(len(points)) if weights is None else weights
    size = (points**2).sum(axis=1)
    floor = 1e-12 * max(float(size.max(initial=0)), 1e-300)  # below it lies rounding, not distance

    def away(i: int) -> np.ndarray:
        d = size - 2 * (points @ points[i]) + size[i]
        return np.where(d > floor, d, 0.0)

    chosen = [int(rng.choice(len(points), p=w / w.sum()))]
    d = away(chosen[0])
    while len(chosen) < min(k, len(points)):
        mass = d * w
        pick = int(rng.choice(len(points), p=mass / mass.sum())) if mass.sum() > 0 else int(np.setdiff1d(np.arange(len(points)), chosen)[0])
        chosen.append(pick)
        d = np.minimum(d, away(pick))
    return points[chosen]


def lloyd(points, centroids, max_iter=15, tol=1e-6, weights=None, empty="keep"):
    """K-means in memory, for node tables. Returns centroids, labels, squared distances, history of sse."""
    w = np.ones(len(points)) if weights is None else weights
    history = []
    for _ in range(max_iter):
        at, d = nearest(points, centroids)
        history.append(float((d * w).sum()))
        mass = np.bincount(at, w, len(centroids))
        sums = np.stack([np.bincount(at, points[:, j] * w, len(centroids)) for j in range(points.shape[1])], axis=1)
        new = np.where(mass[:, None] > 0, sums / np.maximum(mass, 1e-300)[:, None], centroids)
        if empty == "farthest" and (mass == 0).any():
            far = np.argsort(-d)[: int((mass == 0).sum())]
            new[np.flatnonzero(mass == 0)[: len(far)]] = points[far]
        moved = float(((new - centroids) ** 2).sum(axis=1).max())
        centroids = new
        if moved < tol:
            break
    at, d = nearest(points, centroids)
    history.append(float((d * w).sum()))
    return centroids, at, d, history
