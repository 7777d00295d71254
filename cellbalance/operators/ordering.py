"""Orders of cells on a line that keep neighbours close. Computed once; rebalancing only cuts the same line again."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Parts of up to so many cells are ordered whole inside one task; by a dense solver up to ``DENSE_CELLS``, larger ones down to ``SMALL_CELLS`` by coarsening.
LEAF_CELLS = 131_072
DENSE_CELLS, SMALL_CELLS = 2_000, 300


def key_order(df: DataFrame, key: str) -> DataFrame:
    """(cell_id, pos) for keys that are already dense from 0: no sort, no shuffle."""
    return df.select(F.col(key).cast("long").alias("cell_id"), (F.col(key) + 1).cast("long").alias("pos"))


def dense_pos(df: DataFrame, key: str, buckets: int = 256, carry: tuple[str, ...] = ()) -> DataFrame:
    """(cell_id, pos): rank of distinct keys without a window over all rows. With columns to ``carry``, keys must be distinct already.

    Bucket bounds are quantiles, so buckets are even; ranks inside a bucket are shifted by the counts of those before it.
    """
    keys = df.select(F.col(key).cast("long").alias("cell_id"), *carry)
    keys = keys if carry else keys.distinct()
    fractions = [i / buckets for i in range(1, buckets)]
    bounds = keys.agg(F.percentile_approx("cell_id", fractions, 10_000).alias("bounds")).scalar()
    bucketed = keys.withColumn("bounds", bounds).select("cell_id", *carry, F.size(F.filter("bounds", lambda b: b < F.col("cell_id"))).alias("bucket"))
    counts = bucketed.groupBy("bucket").agg(F.count("*").alias("c"))  # at most ``buckets`` rows
    before = counts.select("bucket", (F.sum("c").over(Window.orderBy("bucket")) - F.col("c")).alias("before"))
    inside = F.row_number().over(Window.partitionBy("bucket").orderBy("cell_id"))
    return bucketed.withColumn("r", inside).join(F.broadcast(before), "bucket").select("cell_id", (F.col("before") + F.col("r")).cast("long").alias("pos"), *carry)


def lattice(spark: SparkSession, shape: tuple[int, int, int]) -> DataFrame:
    """(cell_id, ix, iy, iz) of a box lattice, z fastest."""
    nx, ny, nz = shape
    c = F.col("id")
    return spark.range(nx * ny * nz).select(c.alias("cell_id"), F.expr(f"id div {ny * nz}").cast("int").alias("ix"), F.expr(f"(id div {nz}) % {ny}").cast("int").alias("iy"), F.expr(f"id % {nz}").cast("int").alias("iz"))


def lattice_edges(spark: SparkSession, shape: tuple[int, int, int]) -> DataFrame:
    """(a, b): cell ids that share a face, each face once."""
    nx, ny, nz = shape
    cells = lattice(spark, shape)
    steps = [("ix", nx, ny * nz), ("iy", ny, nz), ("iz", nz, 1)]
    found = F.array(*(F.when(F.col(c) < n - 1, F.col("cell_id") + d) for c, n, d in steps))
    return cells.select(F.col("cell_id").alias("a"), F.explode(found).alias("b")).filter("b is not null")


def lattice_order(cells: DataFrame, shape: tuple[int, int, int], kind: str = "axis") -> DataFrame:
    """(cell_id, pos). 'axis': along x, then y, then z, in closed form. 'bisect': halving the longest axis again and again."""
    nx, ny, nz = shape
    if kind == "axis":
        return cells.select("cell_id", ((F.col("ix") * ny + F.col("iy")) * nz + F.col("iz") + 1).cast("long").alias("pos"))

    # Each level halves every part's longest axis; a part's place is the number of cells before it. The levels are steps of
    # one fold, so the expression doesn't grow with them.
    levels = sum(max(0, int(n - 1)).bit_length() for n in shape)
    start = F.struct(*(F.lit(0).alias(f"l{i}") for i in range(3)), *(F.lit(n).alias(f"n{i}") for i, n in enumerate(shape)), F.lit(0).cast("long").alias("before"))

    def halve(s, _level):
        def cut(axis: int):
            low, n, at = s[f"l{axis}"], s[f"n{axis}"], F.col(("ix", "iy", "iz")[axis])
            half = F.floor((n + 1) / 2).cast("int")
            right = at - low >= half
            area = [s[f"n{i}"] for i in range(3) if i != axis]
            lows = [F.when(right, low + half).otherwise(low) if i == axis else s[f"l{i}"] for i in range(3)]
            sizes = [F.when(right, n - half).otherwise(half) if i == axis else s[f"n{i}"] for i in range(3)]
            before = s["before"] + F.when(right, (half * area[0] * area[1]).cast("long")).otherwise(F.lit(0).cast("long"))
            return F.struct(*(c.cast("int").alias(f"l{i}") for i, c in enumerate(lows)), *(c.cast("int").alias(f"n{i}") for i, c in enumerate(sizes)), before.alias("before"))

        return F.when((s["n0"] >= s["n1"]) & (s["n0"] >= s["n2"]), cut(0)).when(s["n1"] >= s["n2"], cut(1)).otherwise(cut(2))

    before = F.aggregate(F.sequence(F.lit(1), F.lit(max(1, levels))), start, halve, lambda s: s["before"])
    return cells.select("cell_id", (before + 1).cast("long").alias("pos"))


def morton_code(columns: list[str], bits: int = 10) -> Column:
    """Bits of the coordinates, interleaved; a sort by it keeps most neighbours close."""
    code, d = F.lit(0).cast("long"), len(columns)
    for bit in range(bits):
        for i, c in enumerate(columns):
            code = code.bitwiseOR(F.shiftleft(F.shiftright(F.col(c).cast("long"), bit).bitwiseAND(F.lit(1).cast("long")), bit * d + (d - 1 - i)))
    return code


def hilbert_code(x: str, y: str, bits: int = 10) -> Column:
    """Place on the plane's Hilbert curve, by rotating quadrants from the top bit down."""
    a, b = F.col(x).cast("long"), F.col(y).cast("long")
    steps = F.sequence(F.lit(bits - 1), F.lit(0), F.lit(-1))

    def step(s, bit):
        side = F.pow(F.lit(2), bit).cast("long")
        rx = F.when(s["x"].bitwiseAND(side) > 0, 1).otherwise(0)
        ry = F.when(s["y"].bitwiseAND(side) > 0, 1).otherwise(0)
        full = F.lit((1 << bits) - 1).cast("long")
        fx, fy = F.when((ry == 0) & (rx == 1), full - s["x"]).otherwise(s["x"]), F.when((ry == 0) & (rx == 1), full - s["y"]).otherwise(s["y"])
        d = s["d"] + side * side * ((3 * rx).bitwiseXOR(ry)).cast("long")
        return F.struct(d.alias("d"), F.when(ry == 0, fy).otherwise(fx).alias("x"), F.when(ry == 0, fx).otherwise(fy).alias("y"))

    return F.aggregate(steps, F.struct(F.lit(0).cast("long").alias("d"), a.alias("x"), b.alias("y")), step, lambda s: s["d"])


def curve_order(cells: DataFrame, columns: list[str], kind: str = "morton", bits: int = 10) -> DataFrame:
    """(cell_id, pos) by a space-filling curve over non-negative integer coordinates; ties by id."""
    code = morton_code(columns, bits) if kind == "morton" else hilbert_code(*columns[:2], bits)
    ranked = cells.select("cell_id", code.alias("code"))
    # ties by id: rank of (code, id), two-level: codes are ranked by bucket, ids inside
    per_code = ranked.groupBy("code").agg(F.count("*").alias("c"))
    codes = dense_pos(per_code, "code").select(F.col("cell_id").alias("code"), F.col("pos").alias("code_pos")).join(per_code, "code")
    from .scan import scan_blocks

    before = scan_blocks(codes.select(F.col("code_pos").alias("pos"), F.col("c").alias("weight"))).select(F.col("pos").alias("code_pos"), "s_prev")
    inside = F.row_number().over(Window.partitionBy("code").orderBy("cell_id"))
    return ranked.withColumn("r", inside).join(codes.select("code", "code_pos"), "code").join(before, "code_pos").select("cell_id", (F.col("s_prev") + F.col("r")).cast("long").alias("pos"))


def line_locality(edges: DataFrame, order: DataFrame) -> DataFrame:
    """One row: mean and largest distance on the line of cells that share a face."""
    a = order.select(F.col("cell_id").alias("a"), F.col("pos").alias("pa"))
    b = order.select(F.col("cell_id").alias("b"), F.col("pos").alias("pb"))
    d = edges.join(a, "a").join(b, "b").select(F.abs(F.col("pa") - F.col("pb")).alias("d"))
    return d.agg(F.round(F.avg("d"), 9).alias("mean_distance"), F.max("d").cast("long").alias("max_distance"))


# ---------------------------------------------------------------- recursive spectral bisection
def spectral_split(ids: np.ndarray, a: np.ndarray, b: np.ndarray, prior: np.ndarray | None = None) -> np.ndarray:
    """Ids of one part in spectral order: split at the median of the Laplacian's second eigenvector, recursively.

    Entries are rounded before they are ranked, ties go by id. The sign is such that the part runs the way of ``prior``, the
    vector that cut it off, so that ends which were neighbours stay neighbours; without one the smallest id lies left.
    """
    if len(ids) < 3:
        return ids[np.lexsort((ids,) if prior is None else (ids, prior))]
    place = {int(i): k for k, i in enumerate(ids)}
    lap = np.zeros((len(ids), len(ids)))
    for x, y in zip(a.tolist(), b.tolist()):
        i, j = place[x], place[y]
        lap[i, j] -= 1
        lap[j, i] -= 1
        lap[i, i] += 1
        lap[j, j] += 1
    vector = np.round(np.linalg.eigh(lap)[1][:, 1], 9)
    first = int(np.argmin(ids))
    along = 0.0 if prior is None else round(float(vector @ (prior - prior.mean())), 9)
    if along < 0 or (along == 0 and (vector[first] > 0 or (vector[first] == 0 and vector.sum() > 0))):
        vector = -vector
    order = np.lexsort((ids, vector))
    half = (len(ids) + 1) // 2
    parts = []
    for side in (order[:half], order[half:]):
        inside = np.isin(a, ids[side]) & np.isin(b, ids[side])
        parts.append(spectral_split(ids[side], a[inside], b[inside], vector[side]))
    return np.concatenate(parts)


def _merged(n: int, a: np.ndarray, b: np.ndarray, w: np.ndarray, level: int) -> np.ndarray:
    """The coarse node, numbered from 0, of each of ``n`` nodes: the rule of ``_coarser`` inside one task. Edges are there in both directions."""
    with np.errstate(over="ignore"):
        draw = np.minimum(a, b).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) ^ (np.maximum(a, b).astype(np.uint64) + np.uint64(level + 1)) * np.uint64(0xBF58476D1CE4E5B9)
        draw = (draw ^ (draw >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)
    order = np.lexsort((b, draw, w, a))
    last = np.flatnonzero(np.append(np.diff(a[order]) != 0, True))
    own = np.arange(n)
    best = own.copy()
    best[a[order[last]]] = b[order[last]]
    mutual = best[best] == own
    parent = np.where(mutual, np.minimum(own, best), own)
    return np.unique(np.where(~mutual & mutual[best], parent[best], parent), return_inverse=True)[1]


def _second_vector(mass: np.ndarray, a: np.ndarray, b: np.ndarray, w: np.ndarray, dense: int, steps: int = 30, level: int = 0) -> np.ndarray:
    """Second eigenvector of a graph with masses, by coarsening until ``dense`` nodes are left, and smoothing on the way back."""
    n = len(mass)
    if n <= dense:
        lap = np.zeros((n, n))
        np.add.at(lap, (a, b), -w)
        lap[np.diag_indices(n)] = -lap.sum(1)
        root = np.sqrt(mass)
        return np.linalg.eigh(lap / root[:, None] / root)[1][:, min(1, n - 1)] / root
    if not len(a):  # one node a component: any values that set them apart
        return np.arange(n, dtype=float)
    up = _merged(n, a, b, w, level)
    m, ca, cb = int(up.max()) + 1, up[a], up[b]
    outer = ca != cb
    keys, at = np.unique(ca[outer] * m + cb[outer], return_inverse=True)
    v = _second_vector(np.bincount(up, mass, m), keys // m, keys % m, np.bincount(at, w[outer], len(keys)), dense, steps, level + 1)[up]
    degree = np.bincount(a, w, n) / mass
    shift = degree.max()
    for _ in range(steps):
        v = v + (np.bincount(a, w * v[b], n) / mass - degree * v) / (2 * shift)
        v = v - (mass @ v) / mass.sum()
        v = v / (v.std() or 1.0)
    return v


def coarse_split(ids: np.ndarray, a: np.ndarray, b: np.ndarray, prior: np.ndarray | None = None) -> np.ndarray:
    """``spectral_split`` of a part that is too large for a dense solver, down to parts of ``SMALL_CELLS``. ``a`` and ``b`` are places in ``ids``."""
    n = len(ids)
    if n <= SMALL_CELLS:
        return spectral_split(ids, ids[a], ids[b], prior)
    vector = np.round(_second_vector(np.ones(n), np.append(a, b), np.append(b, a), np.ones(2 * len(a)), SMALL_CELLS), 9)
    along = 0.0 if prior is None else round(float(vector @ (prior - prior.mean())), 9)
    if along < 0 or (along == 0 and vector[np.argmin(ids)] > 0):
        vector = -vector
    order = np.lexsort((ids, vector))
    parts, place = [], np.empty(n, np.int64)
    for side in np.split(order, [(n + 1) // 2]):
        place[:] = -1
        place[side] = np.arange(len(side))
        inside = (place[a] >= 0) & (place[b] >= 0)
        parts.append(coarse_split(ids[side], place[a[inside]], place[b[inside]], vector[side]))
    return np.concatenate(parts)


def spectral_order(edges: DataFrame, cells: DataFrame, leaf: int = LEAF_CELLS, iterations: int = 6, checkpoint=None) -> DataFrame:
    """(cell_id, pos). All parts above ``leaf`` cells are split level by level, all of them at once: the graph is coarsened by joins
    until a part has at most ``leaf`` nodes, solved there, and refined on the way back; smaller parts are finished, each in one task.

    ``iterations`` are smoothing steps after each refinement. ``checkpoint(df)`` cuts the lineage; the session's reliable checkpoint
    is used where none is given.
    """
    spark = cells.sparkSession
    parts = cells.select("cell_id").withColumn("part", F.lit("")).withColumn("before", F.lit(0).cast("long")).withColumn("prior", F.lit(None).cast("double"))
    sizes = parts.count()
    save = checkpoint or checkpointer(spark)
    both = save(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))))
    while sizes > leaf:
        parts = save(_split_level(parts, both, leaf, iterations, save))
        sizes = parts.groupBy("part").count().agg(F.max("count")).first()[0]
    inner = edges.join(parts.select(F.col("cell_id").alias("a"), F.col("part").alias("pa"), "before"), "a").join(parts.select(F.col("cell_id").alias("b"), F.col("part").alias("pb")), "b").filter("pa = pb")
    none = F.lit(None)
    rows = parts.select("part", "before", F.col("cell_id").alias("a"), none.cast("long").alias("b"), "prior").unionByName(inner.select(F.col("pa").alias("part"), "before", "a", "b", none.cast("double").alias("prior")))

    def finish(pdf: pd.DataFrame) -> pd.DataFrame:
        own = pdf["b"].isna()
        prior = pdf["prior"][own].to_numpy(float)
        ids, (a, b) = pdf["a"][own].to_numpy(np.int64), (pdf[c][~own].to_numpy(np.int64) for c in ("a", "b"))
        prior = None if np.isnan(prior).any() else prior
        if len(ids) <= DENSE_CELLS:
            ids = spectral_split(ids, a, b, prior)
        else:
            order = np.argsort(ids)
            ids, prior = ids[order], None if prior is None else prior[order]
            a, b = np.searchsorted(ids, a), np.searchsorted(ids, b)
            apart = a != b
            ids = coarse_split(ids, a[apart], b[apart], prior)
        return pd.DataFrame({"cell_id": ids, "pos": int(pdf["before"].iloc[0]) + 1 + np.arange(len(ids))})

    return rows.groupBy("part").applyInPandas(finish, "cell_id long, pos long")


def checkpointer(spark: SparkSession):
    where = spark.conf.get("spark.checkpoint.dir", None)
    if where is None and spark.sparkContext.master.startswith("local["):
        import tempfile

        where = tempfile.mkdtemp(prefix="checkpoints-")
    if where is None:
        raise RuntimeError("spark.checkpoint.dir is unset: name a folder that all executors share")
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(where)
    return lambda df: df.checkpoint()


def _coarser(nodes: DataFrame, edges: DataFrame, level: int) -> DataFrame:
    """(id, parent) of ``nodes`` (id, part, mass): ends of edges that are each other's heaviest merge, others join their heaviest one's pair."""
    draw = F.xxhash64(F.least("a", "b"), F.greatest("a", "b"), F.lit(level))
    best = edges.groupBy("a").agg(F.max(F.struct("w", draw, "b"))["b"].alias("b"))
    pairs = best.join(best.select(F.col("b").alias("a"), F.col("a").alias("b")), ["a", "b"])
    merged = pairs.select(F.col("a").alias("id"), F.least("a", "b").alias("parent"))
    joined = best.join(merged.select(F.col("id").alias("b"), F.col("parent").alias("through")), "b").select(F.col("a").alias("id"), "through")
    known = nodes.select("id").join(merged, "id", "left").join(joined, "id", "left")
    return known.select("id", F.coalesce("parent", "through", "id").alias("parent"))


def _smoothed(nodes: DataFrame, edges: DataFrame, vector: DataFrame, steps: int, save) -> DataFrame:
    """``vector`` (id, v) after ``steps`` of shifted power iteration by joins, the mean taken out of each part."""
    degree = edges.groupBy("a").agg(F.sum("w").alias("deg"))
    now = nodes.join(vector, "id").join(degree.withColumnRenamed("a", "id"), "id", "left").select("id", "part", "mass", "v", (F.coalesce("deg", F.lit(0.0)) / F.col("mass")).alias("deg"))
    shift = now.agg(F.max("deg")).first()[0] or 1.0
    for _ in range(steps):
        pulled = edges.join(now.select(F.col("id").alias("b"), F.col("v").alias("vb")), "b").groupBy(F.col("a").alias("id")).agg(F.sum(F.col("w") * F.col("vb")).alias("pull"))
        moved = now.join(pulled, "id", "left").withColumn("v", F.col("v") + (F.coalesce(F.col("pull") / F.col("mass"), F.lit(0.0)) - F.col("deg") * F.col("v")) / (2 * shift))
        stats = moved.groupBy("part").agg((F.sum(F.col("mass") * F.col("v")) / F.sum("mass")).alias("mean"), F.stddev_pop("v").alias("sd"))
        now = save(moved.join(stats, "part").withColumn("v", F.when(F.col("sd") > 0, (F.col("v") - F.col("mean")) / F.col("sd")).otherwise(F.lit(0.0))).drop("mean", "sd", "pull"))
    return now.select("id", "v")


def _coarse_vector(pdf: pd.DataFrame) -> pd.DataFrame:
    """Second eigenvector of one part's coarse graph, its masses taken into account. Rows without b are nodes."""
    own = pdf["b"].isna()
    ids, mass = pdf["a"][own].to_numpy(np.int64), pdf["w"][own].to_numpy(float)
    order = np.argsort(ids)
    ids, mass = ids[order], mass[order]
    i, j = (np.searchsorted(ids, pdf[c][~own].to_numpy(np.int64)) for c in ("a", "b"))
    vector = _second_vector(mass, i, j, pdf["w"][~own].to_numpy(float), DENSE_CELLS)
    return pd.DataFrame({"id": ids, "v": vector})


def _fiedler(parts: DataFrame, inner: DataFrame, leaf: int, steps: int, save) -> DataFrame:
    """(cell_id, v): the second eigenvector of each part, by coarsening and refinement."""
    nodes, edges = parts.select(F.col("cell_id").alias("id"), "part", F.lit(1.0).alias("mass")), inner.withColumn("w", F.lit(1.0))
    levels = []
    most = nodes.groupBy("part").count().agg(F.max("count")).first()[0]
    while most > leaf:
        parent = save(_coarser(nodes, edges, len(levels)))
        up = lambda c: parent.select(F.col("id").alias(c), F.col("parent").alias(f"p{c}"))
        coarse_edges = edges.join(up("a"), "a").join(up("b"), "b").filter("pa <> pb").groupBy(F.col("pa").alias("a"), F.col("pb").alias("b")).agg(F.sum("w").alias("w"))
        coarse = nodes.join(parent, "id").groupBy(F.col("parent").alias("id"), "part").agg(F.sum("mass").alias("mass"))
        levels.append((nodes, edges, parent))
        nodes, edges = save(coarse), save(coarse_edges)
        before, most = most, nodes.groupBy("part").count().agg(F.max("count")).first()[0]
        if most == before:  # what is left has no edges
            raise ValueError(f"a part has {most} components, more than {leaf}: order the components one by one")
    rows = nodes.select("part", F.col("id").alias("a"), F.lit(None).cast("long").alias("b"), F.col("mass").alias("w")).unionByName(edges.join(nodes.select(F.col("id").alias("a"), "part"), "a").select("part", "a", "b", "w"))
    vector = save(rows.groupBy("part").applyInPandas(_coarse_vector, "id long, v double"))
    for fine, fine_edges, parent in reversed(levels):
        spread = parent.join(vector.withColumnRenamed("id", "parent"), "parent").select("id", "v")
        vector = _smoothed(fine, fine_edges, spread, steps, save)
    return vector.select(F.col("id").alias("cell_id"), "v")


def _ranked(vector: DataFrame, buckets: int = 256) -> DataFrame:
    """(cell_id, part, v) with r, the rank by (v, cell_id) in the part, and n, the part's cells; no task sorts more than a bucket."""
    bounds = vector.groupBy("part").agg(F.percentile_approx("v", [i / buckets for i in range(1, buckets)], 10_000).alias("bounds"), F.count("*").alias("n"))
    placed = vector.join(F.broadcast(bounds), "part").withColumn("bucket", F.size(F.filter("bounds", lambda x: x < F.col("v")))).drop("bounds")
    counts = placed.groupBy("part", "bucket").agg(F.count("*").alias("c"))
    before = counts.select("part", "bucket", (F.sum("c").over(Window.partitionBy("part").orderBy("bucket")) - F.col("c")).alias("lower"))
    inside = F.row_number().over(Window.partitionBy("part", "bucket").orderBy("v", "cell_id"))
    return placed.withColumn("inside", inside).join(F.broadcast(before), ["part", "bucket"]).withColumn("r", F.col("lower") + F.col("inside"))


def _split_level(parts: DataFrame, both: DataFrame, leaf: int, iterations: int, save) -> DataFrame:
    """Halve every part at the median of its second eigenvector, which runs the way of the one that cut it off; the first has the smallest id to the left."""
    inner = both.join(parts.select(F.col("cell_id").alias("a"), F.col("part").alias("pa")), "a").join(parts.select(F.col("cell_id").alias("b"), F.col("part").alias("pb")), "b").filter("pa = pb").select("a", "b")
    vector = _fiedler(parts, save(inner), leaf, iterations, save).join(parts, "cell_id")
    sign = vector.groupBy("part").agg(F.min_by("v", "cell_id").alias("lowest"), F.covar_pop("v", "prior").alias("along"))
    against = F.coalesce(F.col("along") < 0, F.col("lowest") > 0)
    signed = vector.join(F.broadcast(sign), "part").select("cell_id", "part", "before", F.round(F.when(against, -F.col("v")).otherwise(F.col("v")), 9).alias("v"))
    half = F.expr("(n + 1) div 2")
    right = F.col("r") > half
    return _ranked(save(signed)).select("cell_id", F.concat("part", F.when(right, "1").otherwise("0")).alias("part"), (F.col("before") + F.when(right, half).otherwise(0)).cast("long").alias("before"), F.col("v").alias("prior"))
