"""Near-duplicate vectors by tiled comparison in the order of principal components.

Vectors are turned into the basis of principal components, so that the leading coordinates hold as much of
a product as can be had. Sorted by length and by the first coordinate they form tiles. Two tiles are compared
only if their boxes of leading coordinates and their largest suffix norms leave the threshold in reach; inside
a pair of tiles the product of the leading coordinates comes first, the rest is bounded by the product of the
suffix norms, and only pairs that can still reach the threshold get a cosine in double precision, from the
vectors as given (double components stay double).

Tiles that stand near each other form groups; a task compares the tiles of two groups, so a tile is sent once
for each group it meets, not once for each tile. Equal vectors are one class with a count, so copies are never
compared among themselves. Defined cases: a vector that is null, zero, or holds nulls or non-finite numbers
links with nothing; vectors of different lengths do not link with each other, those of each length do among
themselves (the RANKED commonest lengths in the order of their own components, others in that of their first
coordinates: as exact, only less sharp); rows that repeat an id are vectors of their own, each with the
component of its own vector, named by the smallest id in it; a null id has component null unless its component
has an id; other columns are ignored; an empty table gives an empty result. A tile yields at most one count and
one link a vector and partner tile, however many pairs there are.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.groups import connected_components
from ..sources.io import stage

TILE = 4096
LEAD = 16
BOX = 8
BLOCK = 512
#: Lengths of vectors that get principal components, up to the longest of LONGEST; tiles of a group; numbers in a tile.
RANKED, LONGEST, GROUP, CELLS = 4, 4096, 8, 1 << 21


def unit(x: np.ndarray) -> np.ndarray:
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _matrix(column: pa.Array, d: int) -> np.ndarray:
    return np.asarray(column.flatten(), np.float64).reshape(-1, d)


def principal_axes(vectors: DataFrame, d: int) -> np.ndarray:
    """Orthonormal basis, leading component first, of all vectors of length d (one d x d sum a task, added up in two steps)."""

    def moments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((d + 1, d + 1))
        for batch in batches:
            z = unit(_matrix(batch.column(0), d))
            z = np.concatenate([z, np.ones((len(z), 1))], axis=1)
            total += z.T @ z
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=["m"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((d + 1) ** 2)
        for batch in batches:
            for m in batch.column(0):
                total += np.frombuffer(m.as_buffer())
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=["m"])

    one = vectors.where(F.size("embedding") == d).select("embedding")
    parts = one.mapInArrow(moments, "m binary").repartition(8).mapInArrow(add, "m binary").collect()
    m = sum((np.frombuffer(bytes(r[0])) for r in parts), np.zeros((d + 1) ** 2)).reshape(d + 1, d + 1)
    n = max(m[d, d], 1.0)
    cov = m[:d, :d] / n - np.outer(m[d, :d], m[d, :d]) / n**2
    return np.linalg.eigh(cov)[1][:, ::-1]


def leading(x: np.ndarray, axes: dict[int, np.ndarray]) -> np.ndarray:
    """The LEAD first coordinates of vectors of one length, made unit, in that length's basis."""
    d = x.shape[1]
    return unit(x) @ axes[d][:, :LEAD] if d in axes else unit(x)[:, :LEAD]


TILED = "part int, k int, d int, size int, keys binary, counts binary, vectors binary, low array<double>, high array<double>, suffix double"


def tiles(classes: DataFrame, axes: dict[int, np.ndarray], kind: str, tile: int = TILE) -> DataFrame:
    """Rows (key, m, embedding) to tiles of one length, in the order of the first leading coordinate."""
    cell = np.float32 if kind == "float" else np.float64

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            d = np.asarray(pc.list_value_length(batch.column("embedding")), np.int32)
            at = np.zeros(len(d))
            for n in np.unique(d).tolist():
                here = np.flatnonzero(d == n)
                at[here] = leading(_matrix(batch.column("embedding").take(pa.array(here)), n), axes)[:, 0]
            yield batch.append_column("d", pa.array(d)).append_column("at", pa.array(at))

    placed = classes.mapInArrow(first, f"key long, m long, embedding array<{kind}>, d int, at double")
    placed = stage(placed, "placed").repartitionByRange("d", "at").sortWithinPartitions("d", "at")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, k, held, n, d = TaskContext.get().partitionId(), 0, [], 0, 0

        def row(batch: pa.RecordBatch) -> pa.RecordBatch:
            x = _matrix(batch.column("embedding"), d)
            z = leading(x, axes)
            rest = np.sqrt(np.maximum(0, 1 - (z[:, :BOX] ** 2).sum(1))).max()
            low, high = (np.pad(v, (0, BOX - len(v))) for v in (z[:, :BOX].min(0), z[:, :BOX].max(0)))
            data = [[part], [k], [d], [len(x)], [np.asarray(batch.column("key"), np.int64).tobytes()], [np.asarray(batch.column("m"), np.int64).tobytes()], [x.astype(cell).tobytes()], [low], [high], [rest]]
            kinds = [pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.list_(pa.float64()), pa.list_(pa.float64()), pa.float64()]
            return pa.RecordBatch.from_arrays([pa.array(a, t) for a, t in zip(data, kinds, strict=True)], names=[c.split()[0] for c in TILED.split(", ")])

        def whole() -> pa.RecordBatch:
            return pa.Table.from_batches(held).combine_chunks().to_batches()[0]

        for batch in batches:
            lengths = np.asarray(batch.column("d"), np.int32)
            edges = np.concatenate(([0], np.flatnonzero(np.diff(lengths)) + 1, [len(lengths)]))
            for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
                if b == a:
                    continue
                if n and lengths[a] != d:
                    yield row(whole())
                    k, n, held = k + 1, 0, []
                d = int(lengths[a])
                held.append(batch.slice(a, b - a))
                n += b - a
                most = max(1, min(tile, CELLS // d))
                while n >= most:
                    full = whole()
                    yield row(full.slice(0, most))
                    k, n = k + 1, n - most
                    held = [full.slice(most)] if n else []
        if n:
            yield row(whole())

    return placed.mapInArrow(cut, TILED)


def forest(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    """Smallest reachable index for each of n nodes, given links."""
    label = np.arange(n)
    while True:
        low = np.minimum(label[a], label[b])
        before = label.copy()
        np.minimum.at(label, a, low)
        np.minimum.at(label, b, low)
        label = label[label]
        if (label == before).all():
            return label


class Links:
    """Links among n vectors, counted and grouped block by block; no pair is kept."""

    def __init__(self, counts: np.ndarray):
        self.counts = counts.astype(np.int64)
        self.links, self.label = np.zeros(len(counts), np.int64), np.arange(len(counts))

    def add(self, i: np.ndarray, j: np.ndarray) -> None:
        np.add.at(self.links, i, self.counts[j])
        np.add.at(self.links, j, self.counts[i])
        a, b = self.label[i], self.label[j]
        apart = a != b
        if apart.any():
            self.label = forest(a[apart], b[apart], len(self.label))[self.label]


def compare(x: np.ndarray, y: np.ndarray, axes: dict[int, np.ndarray], threshold: float, same: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(i, j) of pairs x[i], y[j] at the threshold or over, some at a time; same: pairs i < j of one tile."""
    zx, zy = leading(x, axes), leading(y, axes)
    sx, sy = (np.sqrt(np.maximum(0, 1 - (z * z).sum(1))) for z in (zx, zy))
    nx, ny = np.sqrt((x * x).sum(1)), np.sqrt((y * y).sum(1))
    for a in range(0, len(x), BLOCK):
        for b in range(a if same else 0, len(y), BLOCK):
            bound = zx[a : a + BLOCK] @ zy[b : b + BLOCK].T
            bound += np.outer(sx[a : a + BLOCK], sy[b : b + BLOCK])
            i, j = np.nonzero(bound >= threshold - 1e-9)
            i, j = i + a, j + b
            if same:
                i, j = i[i < j], j[i < j]
            for at in range(0, len(i), 1 << 16):
                p, q = i[at : at + (1 << 16)], j[at : at + (1 << 16)]
                ok = np.einsum("ij,ij->i", x[p], y[q]) / (nx[p] * ny[q]) >= threshold
                yield p[ok], q[ok]


FOUND = "key long, links long, root long"


def compare_groups(rows: DataFrame, axes: dict[int, np.ndarray], kind: str, threshold: float) -> DataFrame:
    """(key, links, root) for each vector that has a link in a pair of tiles.

    rows: (g, h, tile, d, keys, counts, vectors, pairs), those of one pair of groups (g, h) behind each other.
    """
    cell = np.float32 if kind == "float" else np.float64

    def meet(tiles_here: dict, pairs: list) -> Iterator[pa.RecordBatch]:
        for one, two in pairs:
            (x, kx, cx), (y, ky, cy) = tiles_here[one], tiles_here[two]
            same = one == two
            keys, counts = (kx, cx) if same else (np.concatenate([kx, ky]), np.concatenate([cx, cy]))
            found = Links(counts)
            for i, j in compare(x.astype(np.float64), y.astype(np.float64), axes, threshold, same):
                found.add(i, j if same else j + len(x))
            has = found.links > 0
            yield pa.RecordBatch.from_arrays([pa.array(keys[has]), pa.array(found.links[has]), pa.array(keys[found.label][has])], names=["key", "links", "root"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group, here, pairs = None, {}, []
        for batch in batches:
            for k in range(batch.num_rows):
                get = lambda c: batch.column(c)[k]  # noqa: B023, E731
                now = (get("g").as_py(), get("h").as_py())
                if now != group:
                    yield from meet(here, pairs)
                    group, here, pairs = now, {}, [(p["tile"], p["tile_y"]) for p in get("pairs").as_py()]
                numbers = lambda c, t: np.frombuffer(get(c).as_buffer(), t).copy()
                here[get("tile").as_py()] = (numbers("vectors", cell).reshape(-1, get("d").as_py()), numbers("keys", np.int64), numbers("counts", np.int64))
        yield from meet(here, pairs)

    return rows.mapInArrow(run, FOUND)


def linked_vectors(rows: DataFrame, threshold: float = 0.9, tile: int = TILE) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for each row of (vec_id, embedding)."""
    kind = "float" if "float" in dict(rows.dtypes)["embedding"] else "double"
    rows = rows.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast(f"array<{kind}>").alias("embedding"))
    sound = F.col("embedding").isNotNull() & (F.size("embedding") > 0) & F.forall("embedding", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) != float("inf"))) & F.exists("embedding", lambda v: v != 0)
    rows = rows.withColumn("sound", F.coalesce(sound, F.lit(False)))
    whole = rows.where("sound").groupBy("embedding").agg(F.count("*").alias("m"), F.min("vec_id").alias("low"))
    classes = stage(whole.select(F.monotonically_increasing_id().alias("key"), "m", "low", "embedding"), "vectors")
    if not classes.limit(1).count():
        return rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    common = classes.groupBy(F.size("embedding").alias("d")).agg(F.count("*").alias("n")).where(F.col("d") <= LONGEST).orderBy(F.desc("n"), "d").limit(RANKED).collect()
    axes = {r.d: principal_axes(classes, r.d) for r in common}
    made = stage(tiles(classes.select("key", "m", "embedding"), axes, kind, tile), "tiles")
    # tiles are numbered along the order they were cut in: about as many a part
    parts, n_tiles = made.agg(F.max("part") + 1, F.count("*")).first()
    number = (F.col("part").cast("long") * -(-n_tiles // parts) + F.col("k")).alias("place")
    tile_id = F.shiftleft(F.col("part").cast("long"), 32) + F.col("k")
    shape = made.select(tile_id.alias("tile"), F.floor(number / GROUP).alias("g"), "d", "low", "high", "suffix")
    # Boxes too far apart along the first coordinate are in no neighbouring cell: an equi-join, not a cross join.
    reach = float(np.sqrt(max(0.0, 2 - 2 * threshold)))
    cell = lambda c: F.floor(c / (reach or 1e-3))
    x = shape.withColumn("cell", F.explode(F.sequence(cell(F.col("low")[0]), cell(F.col("high")[0]))))
    y = shape.select(*(F.col(c).alias(f"{c}_y") for c in shape.columns), F.explode(F.sequence(cell(F.col("low")[0] - reach), cell(F.col("high")[0] + reach))).alias("cell_y"))
    corner = lambda k: F.greatest(*(F.col(f"{a}")[k] * F.col(f"{b}_y")[k] for a in ("low", "high") for b in ("low", "high")))
    bound = sum((corner(k) for k in range(BOX)), F.col("suffix") * F.col("suffix_y"))
    near = x.join(y, (F.col("cell") == F.col("cell_y")) & (F.col("d") == F.col("d_y")) & (F.col("tile") <= F.col("tile_y")) & (bound >= threshold - 1e-9)).select("g", F.col("g_y").alias("h"), "tile", "tile_y").distinct()
    near = stage(near, "near")
    meetings = near.groupBy("g", "h").agg(F.collect_list(F.struct("tile", "tile_y")).alias("pairs"))  # at most GROUP x GROUP
    n = max(1, meetings.count())
    named = near.select("g", "h", "tile").unionByName(near.select("g", "h", F.col("tile_y").alias("tile"))).distinct()
    data = made.select(tile_id.alias("tile"), "d", "keys", "counts", "vectors")
    sent = named.join(data, "tile").join(meetings, ["g", "h"]).repartition(min(n, 4 * rows.sparkSession.sparkContext.defaultParallelism + n // 16), "g", "h").sortWithinPartitions("g", "h")
    found = stage(compare_groups(sent, axes, kind, threshold), "links")
    links = found.groupBy("key").agg(F.sum("links").alias("links"))
    roots = connected_components(found.where("key <> root").select("key", "root")).withColumnRenamed("node", "key")
    named = classes.select("key", "m", "low", F.col("embedding").alias("e")).join(links, "key", "left").join(roots, "key", "left").withColumn("root", F.coalesce("root", "key"))
    least = named.groupBy("root").agg(F.min("low").alias("component"))
    named = named.join(least, "root").select("e", (F.coalesce("links", F.lit(0)) + F.col("m") - 1).alias("links"), "component")
    out = rows.join(named, F.col("sound") & (F.col("embedding") == F.col("e")), "left")
    out = out.select("vec_id", F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), F.when(F.col("sound"), F.col("component")).otherwise(F.col("vec_id")).alias("component_id"))
    return out.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


def brute_force(ids: list[int], vectors: list, threshold: float) -> pd.DataFrame:
    """All cosines at once, for tests."""
    good = [k for k, v in enumerate(vectors) if v is not None and len(v) and all(c is not None and np.isfinite(c) for c in v) and any(v)]
    links, label = np.zeros(len(ids), np.int64), list(ids)
    for d in sorted({len(vectors[k]) for k in good}):
        mine = [k for k in good if len(vectors[k]) == d]
        x = np.array([vectors[k] for k in mine], np.float64)
        hit = (x @ x.T) / np.outer(np.linalg.norm(x, axis=1), np.linalg.norm(x, axis=1)) >= threshold
        np.fill_diagonal(hit, False)
        links[mine] = hit.sum(1)
        root = forest(*np.nonzero(hit), len(mine))
        for k, r in enumerate(root):
            label[mine[k]] = min(ids[mine[q]] for q in np.flatnonzero(root == r))
    return pd.DataFrame({"vec_id": ids, "n_links": links, "component_id": label})


def op5_pca_tiles(spark, sf_dir: str) -> DataFrame:
    """All vectors, links at a cosine of 0.9."""
    return linked_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
