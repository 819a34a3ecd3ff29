"""Row and column labels: spectral factors of the numeric image, then clustering.

Few columns (``n`` up to ``GRAM_COLUMNS``): one scan adds up the column Gram matrix in numpy, the driver
factors it, and a second scan projects the rows. Many columns: a random range finder with a few power
steps keeps to ``n`` x ``d`` numbers. Rows cluster in Spark, columns on the driver.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from blockpress.operators.cells import bit_slices, is_packed
from blockpress.sources.storage import discard, kept

GRAM_COLUMNS = 4096
#: Share of ones below which products take the ones' places instead of all cells.
SPARSE = 0.02
#: Cells of a packed table that are numbers at once: as many as a core's cache holds.
PRODUCT_CELLS = 1 << 18
#: Rows that a task draws for each start of k-means, numbers in a packed row of points, and points that are labelled at once.
DRAWN, PACKED_NUMBERS, POINTS_AT_ONCE = 1024, 1 << 19, 1 << 13


@dataclass
class Factors:
    rows: DataFrame  # row_id, a ARRAY<DOUBLE>
    columns: np.ndarray  # n x d
    sigma: np.ndarray
    basis: np.ndarray | None = None  # n x d: a row times it is the row's factors


def _matrix(column: pa.Array) -> np.ndarray:
    """A list column with lists of one length as a matrix."""
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1)


class _Ones:
    """A 0/1 matrix with few ones, by the places of these: what products with it need."""

    def __init__(self, n: int, size: np.ndarray, column: np.ndarray):
        self.shape, self.size, self.column = (len(size), n), size, column
        self.first = np.cumsum(size) - size

    @classmethod
    def of(cls, cells: np.ndarray) -> _Ones:
        at, n = np.flatnonzero(cells.view(bool)), cells.shape[1]
        return cls(n, np.diff(np.searchsorted(at, np.arange(len(cells) + 1) * n)), at % n)

    def dense(self) -> np.ndarray:
        out = np.zeros(self.shape)
        out[np.repeat(np.arange(self.shape[0]), self.size), self.column] = 1
        return out

    def __matmul__(self, basis: np.ndarray) -> np.ndarray:
        out = np.zeros((self.shape[0], basis.shape[1]))
        there = self.size > 0
        if there.any():
            out[there] = np.add.reduceat(basis[self.column], self.first[there], axis=0)
        return out

    def back(self, y: np.ndarray, total: np.ndarray) -> None:
        """Adds itself transposed, times ``y``, to ``total``."""
        if len(self.column):
            order = np.argsort(self.column, kind="stable")
            at, first = np.unique(self.column[order], return_index=True)
            total[at] += np.add.reduceat(y[np.repeat(np.arange(self.shape[0]), self.size)[order]], first, axis=0)


def _slices(column: pa.Array, n: int) -> Iterator:
    """Stretches of a column of rows as matrices: lists of numbers, or 0/1 cells packed to bits."""
    if not is_packed(column):
        yield _matrix(column)
        return
    step = max(1, PRODUCT_CELLS // n)
    for cells in bit_slices(column, n):
        if np.count_nonzero(cells) < SPARSE * cells.size:
            yield _Ones.of(cells)
        else:
            yield from (cells[lo : lo + step].astype(np.float64) for lo in range(0, len(cells), step))


#: Rows of a packed table, many to a row: by the places of their ones, or as bits.
STRETCHES = "ids binary, sizes binary, places binary, bits binary"


def by_ones(x: DataFrame, n: int) -> DataFrame:
    """``STRETCHES`` of ``x(row_id, x)`` if its first rows have few ones, else ``x`` itself: products read only the ones then, scan after scan."""
    if not isinstance(x.schema["x"].dataType, T.BinaryType):
        return x
    seen = [np.frombuffer(bytes(r.x), np.uint8) for r in x.select("x").limit(64).collect()]
    if not seen or sum(int(np.unpackbits(r).sum()) for r in seen) >= SPARSE * n * len(seen):
        return x

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, lo = batch.column("row_id").to_numpy(), 0
            for cells in bit_slices(batch.column("x"), n) if batch.num_rows else ():
                mine, lo = ids[lo : lo + len(cells)], lo + len(cells)
                if np.count_nonzero(cells) < SPARSE * cells.size:
                    ones = _Ones.of(cells)
                    held = [mine.astype(np.int64).tobytes(), ones.size.astype(np.int32).tobytes(), ones.column.astype(np.int32).tobytes(), None]
                else:
                    held = [mine.astype(np.int64).tobytes(), None, None, np.packbits(cells, axis=1).tobytes()]
                yield pa.record_batch([pa.array([h], pa.binary()) for h in held], names=[f.split()[0] for f in STRETCHES.split(", ")])

    return kept(x.select("row_id", "x").mapInArrow(emit, STRETCHES), "stretches")


def _matrices(batch: pa.RecordBatch, n: int) -> Iterator[tuple]:
    """Row numbers (where there are some) and matrix of the stretches of a batch of ``x(row_id, x)`` or ``STRETCHES``."""
    if not batch.num_rows:
        return
    if "sizes" not in batch.schema.names:
        ids, lo = batch.column("row_id").to_numpy() if "row_id" in batch.schema.names else None, 0
        for m in _slices(batch.column("x"), n):
            yield None if ids is None else ids[lo : lo + m.shape[0]], m
            lo += m.shape[0]
        return
    waiting: list[tuple] = []

    def joined():
        ids, sizes, places = (np.frombuffer(b"".join(c), t) for c, t in zip(zip(*waiting, strict=True), (np.int64, np.int32, np.int32), strict=True))
        waiting.clear()
        return ids, _Ones(n, sizes.astype(np.int64), places)

    for ids, sizes, places, bits in zip(*[batch.column(f.split()[0]).to_pylist() for f in STRETCHES.split(", ")], strict=True):
        if sizes is not None:
            waiting.append((ids, sizes, places))
            continue
        if waiting:
            yield joined()
        ids = np.frombuffer(ids, np.int64)
        cells = np.unpackbits(np.frombuffer(bits, np.uint8).reshape(len(ids), -1), axis=1, count=n)
        step = max(1, PRODUCT_CELLS // n)
        yield from ((ids[lo : lo + step], cells[lo : lo + step].astype(np.float64)) for lo in range(0, len(cells), step))
    if waiting:
        yield joined()


def sample_rows(x: DataFrame, fraction: float) -> DataFrame:
    """The rows whose hash falls below the fraction: the same ones every time."""
    return x if fraction >= 1 else x.where(F.pmod(F.xxhash64("row_id"), F.lit(1_000_000)) < int(fraction * 1_000_000))


def sample_by_length(x: DataFrame, fraction: float) -> DataFrame:
    """Rows kept with a chance in proportion to their squared length, and scaled so that Gram sums stay right on average."""
    square = F.aggregate("x", F.lit(0.0), lambda a, v: a + v * v)
    sized = x.withColumn("_s", square)
    got = sized.agg(F.sum("_s").alias("s"), F.count("*").alias("m")).first()
    if not got.s:
        return x
    chance = F.least(F.lit(1.0), F.col("_s") * F.lit(fraction * got.m / got.s))
    draw = F.pmod(F.xxhash64("row_id"), F.lit(1_000_000)) / 1_000_000
    kept_ = sized.withColumn("_p", chance).where((F.col("_p") > 0) & (draw < F.col("_p")))
    return kept_.select("row_id", F.transform("x", lambda v: v / F.sqrt(F.col("_p"))).alias("x"))


def gram(x: DataFrame, n: int) -> np.ndarray:
    """Sum of the rows' outer products. A task gives one packed triangle; groups of tasks add up before the driver."""
    upper = np.triu_indices(n)

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((n, n))
        for batch in batches:
            for m in _slices(batch.column("x"), n) if batch.num_rows else ():
                m = m.dense() if isinstance(m, _Ones) else m
                total += m.T @ m
        yield pa.record_batch([pa.array([0]), pa.array([total[upper].tobytes()], pa.binary())], names=["g", "t"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(upper[0]))
        for batch in batches:
            for t in batch.column("t").to_pylist():
                total += np.frombuffer(t)
        yield pa.record_batch([pa.array([0]), pa.array([total.tobytes()], pa.binary())], names=["g", "t"])

    parts = x.select("x").mapInArrow(part, "g long, t binary")
    groups = max(1, int(parts.rdd.getNumPartitions() ** 0.5))
    out = np.zeros((n, n))
    for r in parts.repartition(groups).mapInArrow(add, "g long, t binary").toLocalIterator():
        out[upper] += np.frombuffer(bytes(r.t))
    return out + np.triu(out, 1).T


def project(x: DataFrame, basis: np.ndarray) -> DataFrame:
    """Each row times ``basis``."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                ids, a = (np.concatenate(c) for c in zip(*[(i, m @ basis) for i, m in _matrices(batch, len(basis))], strict=True))
                at = np.arange(len(a) + 1, dtype=np.int64) * basis.shape[1]
                lists = pa.LargeListArray.from_arrays(pa.array(at), pa.array(a.ravel())).cast(pa.list_(pa.float64()))
                yield pa.record_batch([pa.array(ids, pa.int64()), lists], names=["row_id", "a"])

    return (x.select("row_id", "x") if "x" in x.columns else x).mapInArrow(emit, "row_id long, a array<double>")


def transposed_product(x: DataFrame, basis: np.ndarray) -> np.ndarray:
    """X'(X basis) in one scan. A task gives one product; groups of tasks add up before the driver."""
    n, d = basis.shape

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((n, d))
        for batch in batches:
            for _, m in _matrices(batch, n):
                if isinstance(m, _Ones):
                    m.back(m @ basis, total)
                else:
                    total += ((m @ basis).T @ m).T
        yield pa.record_batch([pa.array([total.tobytes()], pa.binary())], names=["t"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(n * d)
        for batch in batches:
            for t in batch.column("t").to_pylist():
                total += np.frombuffer(t)
        yield pa.record_batch([pa.array([total.tobytes()], pa.binary())], names=["t"])

    out = np.zeros((n, d))
    parts = (x.select("x") if "x" in x.columns else x).mapInArrow(part, "t binary")
    held = kept(parts, "products", "none")  # deleted again, where a shuffle of each step would stay
    groups = max(1, int(held.rdd.getNumPartitions() ** 0.5))
    for r in held.coalesce(groups).mapInArrow(add, "t binary").toLocalIterator():
        out += np.frombuffer(bytes(r.t)).reshape(n, d)
    discard(held)
    return out


def _signed(b: np.ndarray) -> np.ndarray:
    """Each vector's largest entry made positive."""
    pick = np.abs(b).argmax(axis=0)
    return b * np.where(b[pick, np.arange(b.shape[1])] < 0, -1.0, 1.0)


def spectral_factors(x: DataFrame, n: int, d: int, solver: str = "auto", fraction: float = 1.0, power_steps: int = 4, seed: int = 42, sampling: str = "uniform") -> Factors:
    """Leading ``d`` singular factors of ``x(row_id, x)``; ``x`` is a list of numbers, or 0/1 cells packed to bits.

    ``solver``: ``auto`` (``gram`` up to ``GRAM_COLUMNS`` columns, else ``power``), ``gram``, ``power`` (block power steps to a tight subspace) or ``sketch`` (random range
    finder, two scans). ``fraction`` below 1 takes the right factors from that share of the rows, drawn
    evenly or, with ``sampling="length"``, by squared length.
    """
    d = min(d, n)
    solver = ("gram" if n <= GRAM_COLUMNS else "power") if solver == "auto" else solver
    part = sample_by_length(x, fraction) if sampling == "length" and fraction < 1 else sample_rows(x, fraction)
    if solver == "gram":
        if n > GRAM_COLUMNS:
            raise ValueError(f"{n} columns: use the power or sketch solver")
        value, vector = np.linalg.eigh(gram(part, n))
        b, s2 = vector[:, ::-1][:, :d], value[::-1][:d]
    else:
        part = by_ones(part, n)
        x = part if fraction >= 1 else x
        wide = min(n, d + 8)
        q, _ = np.linalg.qr(np.random.default_rng(seed).standard_normal((n, wide)))
        for _ in range(power_steps * 3 if solver == "power" else 1):
            q, _ = np.linalg.qr(transposed_product(part, q))
        small = q.T @ transposed_product(part, q)
        value, vector = np.linalg.eigh((small + small.T) / 2)
        b, s2 = q @ vector[:, ::-1][:, :d], value[::-1][:d]
    b, sigma = _signed(b), np.sqrt(np.maximum(s2, 0))
    safe = np.where(sigma > 1e-9 * max(sigma.max(initial=0), 1e-300), sigma, np.inf)
    return Factors(project(x, b / safe), b, sigma, b / safe)


def kmeans_small(points: np.ndarray, k: int, seed: int = 42, starts: int = 5, iterations: int = 100) -> np.ndarray:
    """Labels of a few points on the driver: random starts, best cost; an empty cluster takes the farthest point."""
    k = min(k, len(np.unique(points, axis=0)))
    best, labels = np.inf, np.zeros(len(points), int)
    for s in range(starts):
        rng = np.random.default_rng(seed + s)
        centres = points[rng.choice(len(points), k, replace=False)]
        for _ in range(iterations):
            far = ((points[:, None] - centres[None]) ** 2).sum(axis=2)
            own = far.argmin(axis=1)
            for c in range(k):
                if not (own == c).any():
                    own[far[np.arange(len(points)), own].argmax()] = c
            new = np.stack([points[own == c].mean(axis=0) if (own == c).any() else centres[c] for c in range(k)])
            if np.allclose(new, centres):
                break
            centres = new
        cost = ((points - centres[own]) ** 2).sum()
        if cost < best:
            best, labels = cost, own
    return canonical(labels)


def canonical(labels: np.ndarray) -> np.ndarray:
    """Labels renumbered by size, largest first, ties by first place."""
    names, first, count = np.unique(labels, return_index=True, return_counts=True)
    order = np.lexsort((first, -count))
    rank = np.empty(len(names), int)
    rank[order] = np.arange(len(names))
    return rank[np.searchsorted(names, labels)]


def kmeans_rows(rows: DataFrame, k: int, seed: int = 42, init: str = "random", unit: bool = False) -> DataFrame:
    """``row_id, u``: clusters of the row factors, fitted on all rows.

    ``unit`` clusters the directions of the factors instead of the factors.
    """
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    if k <= 1:
        return rows.select("row_id", F.lit(0).alias("u"))
    a = F.col("a")
    if unit:
        norm = F.sqrt(F.aggregate("a", F.lit(0.0), lambda s, x: s + x * x))
        a = F.transform("a", lambda x: x / F.greatest(norm, F.lit(1e-300)))
    points = rows.select("row_id", array_to_vector(a).alias("features"))
    model = KMeans(k=k, seed=seed, initMode=init, maxIter=50, tol=1e-6).fit(points)
    found = kept(model.transform(points).select("row_id", F.col("prediction").alias("p")), "clusters")
    sizes = sorted((-r.c, r.f, r.p) for r in found.groupBy("p").agg(F.count("*").alias("c"), F.min("row_id").alias("f")).collect())  # k rows
    rank = F.create_map(*[F.lit(x) for i, (_, _, p) in enumerate(sizes) for x in (p, i)])
    return found.select("row_id", rank[F.col("p")].cast("int").alias("u"))


@dataclass
class Starts:
    """Fitted starts of k-means: centres by start, ranks of their clusters by size, and which start each of the asked ones is."""

    specs: list[tuple[int, int, int]]
    centres: list[np.ndarray]
    rank: np.ndarray
    asked: list[int]

    def labels(self, a: np.ndarray) -> np.ndarray:
        """Rows of ``a`` x asked starts."""
        own = _nearest_centres(a, self.specs, self.centres)
        return self.rank[np.arange(len(self.specs)), own][:, self.asked].astype(np.int32)


def _nearest_centres(a: np.ndarray, specs: list[tuple[int, int, int]], now: list[np.ndarray]) -> np.ndarray:
    out = np.zeros((len(a), len(specs)), np.int32)
    for s, ((k, width, _), c) in enumerate(zip(specs, now, strict=True)):
        if k > 1:
            far = (c**2).sum(axis=1)[:, None] - 2 * c @ a[:, :width].T
            least, own = far[0], np.zeros(len(a), np.int32)
            for j in range(1, len(far)):  # the first of equals, as argmin, but a row of points at a time
                own[far[j] < least] = j
                least = np.minimum(least, far[j])
            out[:, s] = own
    return out


def _int_lists(cells: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(cells) + 1, dtype=np.int32) * cells.shape[1]), pa.array(cells.ravel()))


def kmeans_many(rows: DataFrame, specs: list[tuple[int, int, int]], iterations: int = 30, tolerance: float = 1e-3) -> DataFrame:
    """``row_id, us ARRAY<INT>``: one plain start of k-means for each ``(k, width, seed)``, see ``kmeans_starts``."""
    rows = kept(rows.select("row_id", "a"), "points")
    starts = kmeans_starts(rows, specs, iterations, tolerance)

    def label(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield pa.record_batch([batch.column("row_id"), _int_lists(starts.labels(_matrix(batch.column("a"))))], names=["row_id", "us"])

    return rows.mapInArrow(label, "row_id long, us array<int>")


def _drawn_points(packed: DataFrame, seeds: list[int], need: int, draw: int) -> dict[int, list] | None:
    """For each seed the ``need`` different points whose least row comes first by hash, or None where too few of the rows drawn are their point's least.

    Of the rows drawn (the first by hash, see ``kmeans_starts``) those go that another row of the same point precedes; a scan finds these.
    """
    drawn: dict[int, list] = {seed: [] for seed in seeds}
    for r in packed.where("seed is not null").select("seed", "h", "ids", "points").collect():  # ``draw`` rows a task and seed
        h, ids = np.frombuffer(r.h, np.int64), np.frombuffer(r.ids, np.int64)
        drawn[r.seed] += list(zip(h.tolist(), ids.tolist(), np.frombuffer(r.points).reshape(len(ids), -1).tolist(), strict=True))
    rows = packed.where("seed is null").agg(F.sum("m")).first()[0] or 0
    drawn = {seed: sorted(found)[:draw] for seed, found in drawn.items()}
    whole = all(len(found) == rows for found in drawn.values())  # no row was left out
    asked = np.unique(np.array([a for found in drawn.values() for *_, a in found]), axis=0)
    if not len(asked):
        return drawn
    leads = np.unique(asked[:, 0])

    def least(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first: dict[bytes, int] = {}
        names = {a.tobytes() for a in asked}
        for batch in batches:
            for ids, points in zip(batch.column("ids").to_pylist(), batch.column("points").to_pylist(), strict=True):
                ids = np.frombuffer(ids, np.int64)
                a = np.frombuffer(points).reshape(len(ids), -1)
                near = np.flatnonzero(leads[np.minimum(np.searchsorted(leads, a[:, 0]), len(leads) - 1)] == a[:, 0])
                different, at = np.unique(a[near], axis=0, return_inverse=True)
                low = np.full(len(different), np.iinfo(np.int64).max)
                np.minimum.at(low, at, ids[near])
                for point, r in zip(different, low.tolist(), strict=True):
                    key = point.tobytes()
                    if key in names:
                        first[key] = min(r, first.get(key, r))
        yield pa.record_batch([pa.array(list(first), pa.binary()), pa.array(list(first.values()), pa.int64())], names=["a", "r"])

    lows = packed.where("seed is null").select("ids", "points").mapInArrow(least, "a binary, r long").groupBy("a").agg(F.min("r").alias("r"))
    low = {bytes(r.a): r.r for r in lows.collect()}  # a row a point drawn
    out = {seed: [a for _, r, a in found if low[np.array(a).tobytes()] == r][:need] for seed, found in drawn.items()}
    return out if whole or all(len(found) >= need for found in out.values()) else None


def kmeans_starts(rows: DataFrame, specs: list[tuple[int, int, int]], iterations: int = 30, tolerance: float = 1e-3) -> Starts:
    """One plain start of k-means on ``rows(row_id, a)`` for each ``(k, width, seed)``, all in the same scans.

    Rows are packed, many to a row of the stored table. Centres begin at different points drawn by hash. Where many rows
    are equal, equal points become one, counted as often as they are. A scan adds up each cluster's points in its tasks; what
    reaches the driver is a sum for each start and cluster. It ends when no centre moves by more than
    ``tolerance`` of their spread. A centre without points stays. Ranks go by size.
    """
    asked, specs = specs, list(dict.fromkeys(specs))
    most = max((k for k, _, _ in specs), default=1)
    seeds, draw = sorted({seed for k, _, seed in specs if k > 1}), max(DRAWN, 8 * most)
    names = ["m", "ids", "points", "times", "seed", "h"]

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple | None] = [None] * len(seeds)
        waiting: list[tuple] = []

        def row(ids, a, times=None, seed=None, h=None):
            cells = [[len(ids)], [ids.astype(np.int64).tobytes()], [np.ascontiguousarray(a, np.float64).tobytes()], [None if times is None else times.astype(np.int64).tobytes()], [seed], [None if h is None else h.tobytes()]]
            return pa.record_batch([pa.array(c, t) for c, t in zip(cells, (pa.int64(), pa.binary(), pa.binary(), pa.binary(), pa.int32(), pa.binary()), strict=True)], names=names)

        def joined():
            return row(*[np.concatenate(x) if x[0] is not None else None for x in zip(*waiting, strict=True)])

        for batch in batches:
            if not batch.num_rows:
                continue
            ids, a = batch.column("row_id").to_numpy(), _matrix(batch.column("a")) + 0.0  # no negative zeros
            times = batch.column("n").to_numpy() if "n" in batch.schema.names else None
            if seeds:
                h = batch.column("h").flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)
                for j in range(len(seeds)):
                    new = (h[:, j], ids, a)
                    if held[j] is not None:
                        near = new[0] <= held[j][0][-1] if len(held[j][0]) == draw else slice(None)
                        new = tuple(np.concatenate([x, y[near]]) for x, y in zip(held[j], new, strict=True))
                    first = np.lexsort((new[1], new[0]))[:draw]
                    held[j] = tuple(x[first] for x in new)
            waiting.append((ids, a, times))
            if sum(x[1].size for x in waiting) >= PACKED_NUMBERS:
                yield joined()
                waiting.clear()
        if waiting:
            yield joined()
        for j, x in enumerate(held):
            if x is not None:
                yield row(x[1], x[2], None, seeds[j], x[0])

    def packed_rows(df: DataFrame) -> DataFrame:
        hashed = df.withColumn("h", F.array(*[F.xxhash64("row_id", F.lit(x)) for x in seeds])) if seeds else df
        return kept(hashed.mapInArrow(pack, "m long, ids binary, points binary, times binary, seed int, h binary"), "packed-points", "none")

    table = packed_rows(rows.select("row_id", "a"))
    drawn = _drawn_points(table, seeds, 4 * most, draw) if seeds else {}
    if drawn is None:
        table = packed_rows(rows.groupBy("a").agg(F.min("row_id").alias("row_id"), F.count("*").alias("n")))
        drawn = _drawn_points(table, seeds, 4 * most, draw)
        if drawn is None:  # all points are different now
            raise ValueError("points drawn are not different")
    points = table.where("seed is null").select("points", "times", "m")
    centres: list[np.ndarray] = []
    for k, width, seed in specs:
        seen: list[list[float]] = []
        for a in drawn.get(seed, []) if k > 1 else []:
            if list(a[:width]) not in seen and len(seen) < k:
                seen.append(list(a[:width]))
        centres.append(np.array(seen or [[0.0] * width]))

    live = [s for s, (k, _, _) in enumerate(specs) if k > 1]

    def sums(now: list[np.ndarray]) -> dict[int, np.ndarray]:
        """For each start sums of the clusters' points, and their numbers."""

        def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = {s: np.zeros((len(now[s]), specs[s][1] + 1)) for s in live}
            for batch in batches:
                for blob, times, m in zip(*[batch.column(c).to_pylist() for c in ("points", "times", "m")], strict=True):
                    whole = np.frombuffer(blob).reshape(m, -1)
                    counted = None if times is None else np.frombuffer(times, np.int64).astype(np.float64)
                    for lo in range(0, m, POINTS_AT_ONCE):
                        a, n = whole[lo : lo + POINTS_AT_ONCE], None if counted is None else counted[lo : lo + POINTS_AT_ONCE]
                        own = _nearest_centres(a, specs, now)
                        for s in live:
                            mine = own[:, s]
                            member = (np.arange(len(now[s]))[:, None] == mine).astype(np.float64)
                            member = member if n is None else member * n
                            total[s][:, :-1] += member @ a[:, : specs[s][1]]
                            total[s][:, -1] += np.bincount(mine, n, minlength=len(now[s]))
            yield pa.record_batch([pa.array(live, pa.int32()), pa.array([total[s].ravel().tolist() for s in live], pa.list_(pa.float64()))], names=["s", "t"])

        found = points.mapInArrow(part, "s int, t array<double>")
        out = {s: np.zeros(now[s].shape[0] * (specs[s][1] + 1)) for s in live}
        for r in found.select("s", F.posexplode("t").alias("j", "x")).groupBy("s", "j").agg(F.sum("x").alias("x")).collect():  # starts x clusters x widths
            out[r.s][r.j] = r.x
        return {s: t.reshape(len(now[s]), -1) for s, t in out.items()}

    for _ in range(iterations if live else 0):
        moved = False
        for s, t in sums(centres).items():
            new = np.where(t[:, -1:] > 0, t[:, :-1] / np.maximum(t[:, -1:], 1), centres[s])
            moved |= np.abs(new - centres[s]).max(initial=0) > tolerance * max(np.abs(new - new.mean(axis=0)).max(initial=0), 1e-300)
            centres[s] = new
        if not moved:
            break
    rank = np.zeros((len(specs), most), np.int32)
    for s, t in (sums(centres) if live else {}).items():
        rank[s, np.lexsort((np.arange(len(t)), -t[:, -1]))] = np.arange(len(t))
    discard(table)
    return Starts(specs, centres, rank, [specs.index(x) for x in asked])


def labelled(codes: DataFrame, basis: np.ndarray, starts: Starts) -> DataFrame:
    """``row_id, us, codes`` of ``codes(row_id, codes)``: labels under each start, of the rows' factors, in one pass and without a join."""
    kind = codes.schema["codes"].dataType.simpleString()

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                a = np.concatenate([m @ basis for m in _slices(batch.column("codes"), len(basis))]) + 0.0
                yield pa.record_batch([batch.column("row_id"), _int_lists(starts.labels(a)), batch.column("codes")], names=["row_id", "us", "codes"])

    return codes.select("row_id", "codes").mapInArrow(emit, f"row_id long, us array<int>, codes {kind}")


def threshold_labels(points: np.ndarray, theta: float) -> np.ndarray:
    """Components of the graph that joins points no farther apart than ``theta`` times their mean norm."""
    n, norm = len(points), np.linalg.norm(points, axis=1)
    label = np.arange(n)
    for i in range(n):
        near = np.flatnonzero(np.linalg.norm(points - points[i], axis=1) <= theta * (norm + norm[i]) / 2)
        for j in np.unique(label[near]):
            if j != label[i]:
                label[label == j] = label[i]
    return canonical(label)


def threshold_rows(rows: DataFrame, theta: float) -> DataFrame:
    """``row_id, u``: components of the threshold graph on rows.

    Points meet in cells: of the norm's logarithm and the direction, at the graph's own grain and with
    every neighbouring cell, so only close points are compared; equal points are one. The links' exact
    rule is tested on those pairs, and components come by star contraction.
    """
    from blockpress.operators.components import connected_components

    d = len(rows.first().a)
    same = kept(rows.groupBy("a").agg(F.min("row_id").alias("node")), "points")
    grain = max(theta * 1.1, 1e-9)
    norm = F.sqrt(F.aggregate("a", F.lit(0.0), lambda s, x: s + x * x))
    cells = F.concat(F.array(F.floor(F.log(F.greatest(norm, F.lit(1e-300))) / grain)), F.transform("a", lambda x: F.floor(x / F.greatest(norm, F.lit(1e-300)) / (2 * grain))))
    own = same.select("node", "a", norm.alias("r"), cells.alias("cell"))
    around = own
    for k in range(d + 1):
        step = F.transform(F.array(F.lit(-1), F.lit(0), F.lit(1)), lambda s, k=k: F.transform("cell", lambda x, i: F.when(i == k, x + s).otherwise(x)))
        around = around.withColumn("cell", F.explode(step))
    a, b = own.select(F.col("node").alias("a"), F.col("a").alias("x"), F.col("r").alias("rx"), "cell"), around.select(F.col("node").alias("b"), F.col("a").alias("y"), F.col("r").alias("ry"), "cell")
    gap = F.sqrt(F.aggregate(F.zip_with("x", "y", lambda p, q: (p - q) * (p - q)), F.lit(0.0), lambda s, v: s + v))
    links = a.join(b, "cell").where("a < b").where(gap <= theta * (F.col("rx") + F.col("ry")) / 2).select("a", "b").distinct()
    found = kept(connected_components(links), "threshold")
    named = rows.join(same, "a").join(found, "node", "left").select("row_id", F.coalesce("component", "node").alias("c"))
    named = kept(named, "threshold-rows")
    from pyspark.sql.window import Window

    sizes = named.groupBy("c").agg(F.count("*").alias("n"))
    ranks = sizes.select("c", (F.row_number().over(Window.orderBy(F.desc("n"), "c")) - 1).alias("u"))  # a row for each component
    return named.join(ranks, "c").select("row_id", "u")


@dataclass
class Latents:
    rows: DataFrame  # row_id, u
    columns: np.ndarray  # label of each column
    sigma: np.ndarray


def spectral_latents(x: DataFrame, n: int, k_r: int, k_c: int, n_components: str | int = "k-1", solver: str = "auto", cluster: str = "kmeans", fraction: float = 1.0, seed: int = 42, init: str = "random", theta: float = 0.05, unit: bool = False, factors: Factors | None = None) -> Latents:
    """Labels of rows and columns of ``x(row_id, x)``.

    Sizes may differ; ``k_c = n`` gives each column its own label, 1 on a side means no labels there.
    ``n_components``: ``"k-1"``, ``"k"`` or a number.
    """
    width = lambda k: max(1, k - 1 if n_components == "k-1" else k if n_components == "k" else int(n_components))
    d = max(width(k_r), width(min(k_c, n) if k_c < n else 1))
    if factors is None:
        factors = spectral_factors(x, n, d, solver, fraction, seed=seed)
    if cluster == "threshold":
        return Latents(threshold_rows(factors.rows, theta), threshold_labels(factors.columns, theta), factors.sigma)
    mine = factors.rows.select("row_id", F.slice("a", 1, width(k_r)).alias("a"))
    rows = kmeans_rows(mine, k_r, seed, init, unit)
    if k_c >= n:
        columns = np.arange(n)
    elif k_c <= 1:
        columns = np.zeros(n, int)
    else:
        columns = kmeans_small(factors.columns[:, : width(k_c)], k_c, seed)
    return Latents(rows, columns, factors.sigma)
