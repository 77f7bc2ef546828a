"""Title vectors, distances and density clusters."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.ml.feature import BucketedRandomProjectionLSH
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from reportgraph.functions.vectors import euclidean, mean_vector
from reportgraph.operators.components import connected_components
from reportgraph.sources.io import checkpointed


def distinct_titles(reports: DataFrame, title_col: str = "title", id_col: str = "report_id") -> DataFrame:
    """``id, title, weight``: one row for each normalised title; monitors repeat theirs, so this is far smaller than the reports."""
    t = F.lower(F.trim(F.regexp_replace(F.col(title_col), r"\s+", " ")))
    return reports.groupBy(t.alias("title")).agg(F.min(id_col).alias("id"), F.count("*").alias("weight")).where("title <> ''")


def embed(titles: DataFrame, dim: int = 100) -> DataFrame:
    """Adds ``vector``, the mean of the title's word vectors."""

    @F.pandas_udf("array<double>")
    def vec(t: pd.Series) -> pd.Series:
        import re

        return t.map(lambda x: mean_vector(re.findall(r"[^\W\d_]+", x or ""), dim).tolist())

    return titles.withColumn("vector", vec("title"))


BLOCK = 512


def neighbour_pairs(points: DataFrame, eps: float, id_col: str = "id", vec_col: str = "vector") -> DataFrame:
    """``a, b, distance`` of all pairs a < b within ``eps``.

    The distance to a fixed pivot differs by at most the distance of two points, so points are dealt by
    cells of width ``eps`` of it, and each cell is compared with itself and the next. Cells are cut into blocks, and
    blocks are paired, so a crowded cell is spread over many tasks.
    """
    first = points.orderBy(id_col).limit(1).select(F.col(vec_col).alias("pivot"))
    p = points.select(F.col(id_col).alias("id"), F.col(vec_col).cast("array<double>").alias("v")).crossJoin(F.broadcast(first.withColumn("pivot", F.col("pivot").cast("array<double>"))))
    p = p.withColumn("cell", F.floor(euclidean(F.col("v"), F.col("pivot")) / eps)).drop("pivot")
    sizes = p.groupBy("cell").agg(F.count("*").alias("n")).withColumn("blocks", F.ceil(F.col("n") / BLOCK))
    p = p.join(sizes.select("cell", "blocks"), "cell").withColumn("block", F.pmod(F.xxhash64("id"), F.col("blocks")))
    packed = p.groupBy("cell", "block").agg(F.collect_list(F.struct("id", "v")).alias("points"))
    left = packed.select(F.col("cell").alias("lc"), F.col("block").alias("lb"), F.col("points").alias("lp"))
    right = packed.select(F.explode(F.array(F.col("cell"), F.col("cell") - 1)).alias("lc"), F.col("cell").alias("rc"), F.col("block").alias("rb"), F.col("points").alias("rp"))
    blocks = left.join(right, "lc").where((F.col("rc") > F.col("lc")) | (F.col("rb") >= F.col("lb")))

    def compare(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in batches:
            for lc, lb, lp, rc, rb, rp in zip(part["lc"], part["lb"], part["lp"], part["rc"], part["rb"], part["rp"]):
                a_id, b_id = np.array([x["id"] for x in lp]), np.array([x["id"] for x in rp])
                a, b = np.stack([x["v"] for x in lp]), np.stack([x["v"] for x in rp])
                d = np.sqrt(np.maximum(0, (a**2).sum(1)[:, None] + (b**2).sum(1)[None] - 2 * a @ b.T))
                i, j = np.nonzero(d <= eps + 1e-7)
                exact = np.sqrt(((a[i] - b[j]) ** 2).sum(1))
                ok = (exact <= eps) & ((a_id[i] < b_id[j]) if (lc, lb) == (rc, rb) else np.ones(len(i), bool))
                lo, hi = np.minimum(a_id[i], b_id[j])[ok], np.maximum(a_id[i], b_id[j])[ok]
                yield pd.DataFrame({"a": lo.astype("int64"), "b": hi.astype("int64"), "distance": exact[ok]})

    return blocks.select("lc", "lb", "lp", "rc", "rb", "rp").mapInPandas(compare, "a long, b long, distance double")


def _packs(points: DataFrame, keys: list[str], size: int) -> DataFrame:
    """``*keys, block, ids, v, codes``: points (``id, v, codes`` and whole numbers ``keys``) of equal keys in blocks of about ``size``, as bytes, written once."""
    counts = points.groupBy(*keys).agg(F.count("*").alias("n")).select(*keys, F.ceil(F.col("n") / size).alias("blocks"))
    p = points.join(counts, keys) if keys else points.crossJoin(F.broadcast(counts))
    p = p.withColumn("block", F.pmod(F.xxhash64("id"), F.col("blocks"))).drop("blocks")

    def pack(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id")
        head = pdf.iloc[:1][[*keys, "block"]].reset_index(drop=True)
        return head.assign(ids=[pdf["id"].to_numpy("<i8").tobytes()], v=[np.stack(pdf["v"]).astype("<f8").tobytes()], codes=[np.stack(pdf["codes"]).astype("<i8").tobytes()])

    schema = ", ".join(f"{c} long" for c in [*keys, "block"]) + ", ids binary, v binary, codes binary"
    return checkpointed(p.groupBy(*keys, "block").applyInPandas(pack, schema))


def _unpacked(ids: bytes, v: bytes, codes: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    i = np.frombuffer(ids, "<i8")
    return i, np.frombuffer(v, "<f8").reshape(len(i), -1), np.frombuffer(codes, "<i8").reshape(len(i), -1)


def neighbour_pairs_hashed(points: DataFrame, eps: float, id_col: str = "id", vec_col: str = "vector", width: float | None = None, tables: int = 6, seed: int = 7, block: int = 2048) -> DataFrame:
    """``a, b, distance`` of pairs a < b within ``eps`` that share a bucket of random projections; it may miss some, never adds one.

    A bucket may hold most points, so its pairs are not made as rows: its points are packed in blocks, and pairs of blocks are compared
    as arrays. Points that meet in several buckets are a pair in the first of them only.
    """
    rows = points.select(F.col(id_col).cast("long").alias("id"), array_to_vector(F.col(vec_col).cast("array<double>")).alias("features"))
    model = BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=width or 2 * eps, numHashTables=tables, seed=seed).fit(rows)
    code = F.array(*[vector_to_array(F.get("hashes", F.lit(t)))[0].cast("long") for t in range(tables)])
    rows = model.transform(rows).select("id", vector_to_array("features").alias("v"), code.alias("codes"))
    cells = rows.select("*", F.posexplode("codes").alias("place", "bucket")).withColumn("place", F.col("place").cast("long"))
    packs = _packs(cells, ["place", "bucket"], block)
    left = packs.select("place", "bucket", F.col("block").alias("lb"), *[F.col(c).alias(f"l_{c}") for c in ("ids", "v", "codes")])
    right = packs.select("place", "bucket", F.col("block").alias("rb"), *[F.col(c).alias(f"r_{c}") for c in ("ids", "v", "codes")])
    pairs = left.join(right, ["place", "bucket"]).where("rb >= lb").drop("bucket")

    def compare(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in batches:
            for place, lb, li, lv, lc, rb, ri, rv, rc in part.itertuples(index=False):
                (a_id, a, a_code), (b_id, b, b_code) = _unpacked(li, lv, lc), _unpacked(ri, rv, rc)
                length = (b**2).sum(1)[None]
                for s in range(0, len(a), 512):
                    d2 = (a[s : s + 512] ** 2).sum(1)[:, None] + length - 2 * a[s : s + 512] @ b.T
                    i, j = np.nonzero(d2 <= (eps + 1e-7) ** 2 + 1e-9)
                    i += s
                    exact = np.sqrt(((a[i] - b[j]) ** 2).sum(1))
                    ok = (exact <= eps) & ((a_code[i] == b_code[j]).argmax(1) == place)
                    ok &= (a_id[i] < b_id[j]) if lb == rb else True
                    yield pd.DataFrame({"a": np.minimum(a_id[i], b_id[j])[ok], "b": np.maximum(a_id[i], b_id[j])[ok], "distance": exact[ok]})

    return pairs.mapInPandas(compare, "a long, b long, distance double")


def nearest(points: DataFrame, k: int, id_col: str = "id", vec_col: str = "vector", block: int = 4096) -> DataFrame:
    """``id, other, distance, rank`` of the ``k`` nearest other points, exactly (ties: the smaller id).

    Points are packed in blocks by hash, which are written once; pairs of blocks are compared, and a task gives back ``k`` rows for each
    point of a block that it has compared with one or more others in a row. So nothing is collected, and no point is shuffled more than once.
    """
    none = F.array().cast("array<long>")
    packs = _packs(points.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("v"), none.alias("codes")), [], block)
    names = ["ids", "v", "codes"]
    pairs = packs.select(*[F.col(c).alias(f"q_{c}") for c in names]).crossJoin(packs.select(*[F.col(c).alias(f"c_{c}") for c in names]))

    def rows_of(asked: bytes, best: list[tuple[np.ndarray, np.ndarray]]) -> pd.DataFrame:
        other, distance = (np.concatenate(c) for c in zip(*best))
        got = pd.DataFrame({"id": np.repeat(np.frombuffer(asked, "<i8"), other.shape[1]), "other": other.ravel(), "distance": distance.ravel()})
        return got[np.isfinite(got["distance"])]

    def compare(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        asked, best = b"", []
        for part in batches:
            for row in part.itertuples(index=False):
                if best and row[0] != asked:
                    yield rows_of(asked, best)
                    best = []
                asked = row[0]
                (asking, q, _), (ids, x, _) = _unpacked(*row[:3]), _unpacked(*row[3:])
                length, before, best = (x**2).sum(1), best, []
                for s in range(0, len(q), 512):
                    mine, y = asking[s : s + 512], q[s : s + 512]
                    d = (y**2).sum(1)[:, None] + length[None] - 2 * y @ x.T
                    d[mine[:, None] == ids[None]] = np.inf
                    # A few more than k are measured again without the loss of digits that the product form has.
                    at = np.argpartition(d, min(k + 8, len(ids)) - 1, axis=1)[:, : k + 8]
                    exact = np.sqrt(((y[:, None, :] - x[at]) ** 2).sum(-1))
                    exact[mine[:, None] == ids[at]] = np.inf
                    other = ids[at]
                    if before:
                        other, exact = np.concatenate([before[s // 512][0], other], 1), np.concatenate([before[s // 512][1], exact], 1)
                    order = np.lexsort((other, exact), axis=1)[:, :k]
                    best.append((np.take_along_axis(other, order, 1), np.take_along_axis(exact, order, 1)))
        if best:
            yield rows_of(asked, best)

    got = pairs.mapInPandas(compare, "id long, other long, distance double")
    w = Window.partitionBy("id").orderBy("distance", "other")
    return got.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def k_distances(points: DataFrame, k: int, id_col: str = "id", vec_col: str = "vector", block: int = 4096) -> DataFrame:
    """``id, k_distance`` to the k-th nearest other point."""
    return nearest(points, k, id_col, vec_col, block).where(F.col("rank") == k).select("id", F.col("distance").alias("k_distance"))


def elbow(distances: DataFrame) -> DataFrame:
    """The k-distance farthest from the chord of the sorted curve; the curve is read at 1000 quantiles."""
    q = [i / 1000 for i in range(1001)]
    curve = distances.agg(F.percentile("k_distance", q).alias("c")).select(F.posexplode("c").alias("i", "d"))
    ends = curve.agg(F.min("d").alias("lo"), F.max("d").alias("hi"))
    off = curve.crossJoin(F.broadcast(ends)).withColumn("off", F.col("i") / 1000 - F.try_divide(F.col("d") - F.col("lo"), F.col("hi") - F.col("lo")))
    return off.agg(F.max_by("d", F.col("off")).alias("eps"))


def dbscan(points: DataFrame, eps: float, min_pts: int, id_col: str = "id", vec_col: str = "vector", weight_col: str | None = None, method: str = "blocked") -> DataFrame:
    """``id, cluster_id``: -1 for noise, else the smallest core of the cluster.

    A core has points of weight ``min_pts`` within ``eps``, itself included; clusters are components of cores; a border point
    joins its nearest core's (ties: the smallest id). ``method`` 'hashed' looks for neighbours by random projections; else blocks of points are
    compared, and their pairs are never listed.
    """
    w = F.col(weight_col).cast("double") if weight_col else F.lit(1.0)
    pts = points.select(F.col(id_col).alias("id"), w.alias("w"))
    if method == "blocked":
        return _dbscan_in_blocks(points.select(F.col(id_col).alias("id"), F.col(vec_col).cast("array<double>").alias("v"), w.alias("w")), eps, min_pts)
    pairs = checkpointed(neighbour_pairs_hashed(points, eps, id_col, vec_col))
    both = pairs.select("a", "b", "distance").unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"), "distance"))
    mass = both.join(pts.withColumnRenamed("id", "b"), "b").groupBy(F.col("a").alias("id")).agg(F.sum("w").alias("near"))
    cores = pts.join(mass, "id", "left").where(F.col("w") + F.coalesce("near", F.lit(0.0)) >= min_pts).select("id")
    ca, cb = cores.withColumnRenamed("id", "a"), cores.withColumnRenamed("id", "b")
    linked = pairs.join(ca, "a", "left_semi").join(cb, "b", "left_semi")
    comp = connected_components(linked, "a", "b").withColumnRenamed("node", "id")
    core_cluster = cores.join(comp, "id", "left").select("id", F.coalesce("component", "id").alias("cluster_id"))
    border = both.join(core_cluster.withColumnRenamed("id", "b"), "b").join(ca, "a", "left_anti")
    border = border.groupBy(F.col("a").alias("id")).agg(F.min(F.struct("distance", "b", "cluster_id"))["cluster_id"].alias("border_cluster"))
    return pts.select("id").join(core_cluster, "id", "left").join(border, "id", "left").select("id", F.coalesce("cluster_id", "border_cluster", F.lit(-1)).alias("cluster_id"))


#: Points of a block, about, that clusters are looked for in.
CROWD = 2048


def _within(a: np.ndarray, b: np.ndarray, eps: float) -> np.ndarray:
    """Which rows of ``a`` are within ``eps`` of which of ``b``; pairs that the loss of digits of the product form leaves open are measured again."""
    size = (a**2).sum(1)[:, None] + (b**2).sum(1)[None]
    gap = size - 2 * a @ b.T - eps * eps
    near = gap <= 0
    i, j = np.nonzero(np.abs(gap) <= 1e-9 * size)
    for s in range(0, len(i), 65_536):
        p, q = i[s : s + 65_536], j[s : s + 65_536]
        near[p, q] = np.sqrt(((a[p] - b[q]) ** 2).sum(1)) <= eps
    return near


def _groups(hit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each row and each column of a table of links the first row of its component, -1 without a link."""
    rows, cols = np.full(hit.shape[0], -1), np.full(hit.shape[1], -1)
    for r in np.flatnonzero(hit.any(1)):
        new = np.array([r]) if rows[r] < 0 else np.array([], int)
        rows[new] = r
        while len(new):
            across = np.flatnonzero(hit[new].any(0) & (cols < 0))
            cols[across] = r
            new = np.flatnonzero(hit[:, across].any(1) & (rows < 0))
            rows[new] = r
    return rows, cols


def _block_packs(points: DataFrame, eps: float, linked: bool) -> DataFrame:
    """``cell, block, ids, v, w, lead``: points (``id, v, w, cell``) in blocks of one cell as bytes, written once; ``lead`` are places of the firsts of their components in the block, if ``linked``."""
    counts = points.groupBy("cell").agg(F.ceil(F.count("*") / CROWD).alias("blocks"))
    p = points.join(counts, "cell").withColumn("block", F.pmod(F.xxhash64("id"), F.col("blocks"))).drop("blocks")

    def pack(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id")
        v, lead = np.stack(pdf["v"]).astype("<f8"), np.arange(len(pdf))
        if linked:
            lead = _groups(np.concatenate([_within(v[s : s + 512], v, eps) for s in range(0, len(v), 512)]))[0]
        head = pdf.iloc[:1][["cell", "block"]].reset_index(drop=True)
        return head.assign(ids=[pdf["id"].to_numpy("<i8").tobytes()], v=[v.tobytes()], w=[pdf["w"].to_numpy("<f8").tobytes()], lead=[lead.astype("<i8").tobytes()])

    tasks = 2 * points.sparkSession.sparkContext.defaultParallelism
    return checkpointed(p.repartition(tasks, "cell", "block").groupBy("cell", "block").applyInPandas(pack, "cell long, block long, ids binary, v binary, w binary, lead binary"))


def _met(left: DataFrame, right: DataFrame, same: bool, work, schema: str) -> DataFrame:
    """What ``work(equal, left block, right block)`` yields of all blocks in a cell or in adjacent ones; with ``same`` both sides are one table and each pair meets once.

    Pairs of blocks are dealt by pairs of partitions, so a crowded cell is the work of all tasks and no block is shuffled.
    """
    l, r = (t.select(*[F.col(c).alias(f"{side}_{c}") for c in t.columns]) for t, side in ((left, "l"), (right, "r")))
    far = F.col("r_cell") - F.col("l_cell")
    once = (far.between(0, 1) & ((far > 0) | (F.col("r_block") >= F.col("l_block")))) if same else far.between(-1, 1)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in batches:
            for row in part.itertuples(index=False):
                a, b = ([np.frombuffer(x, t) for x, t in zip(side, ("<i8", "<f8", "<f8", "<i8"))] for side in (row[2:6], row[8:12]))
                a[1], b[1] = a[1].reshape(len(a[0]), -1), b[1].reshape(len(b[0]), -1)
                yield pd.DataFrame(work(same and row[:2] == row[6:8], a, b))

    return l.crossJoin(r).where(once).mapInPandas(run, schema)


def _dbscan_in_blocks(points: DataFrame, eps: float, min_pts: int) -> DataFrame:
    """``dbscan`` of ``id, v, w``: no pair of points is written.

    Points lie in cells by their distance to a pivot, ``eps`` wide at least, and in blocks of these. One pass over the pairs of near blocks adds up the
    weights around each point; a second one, over cores alone, links the components of whole blocks; a third looks for the nearest core of the other points.
    """
    first = points.orderBy("id").limit(1).select(F.col("v").alias("pivot"))
    p = checkpointed(points.crossJoin(F.broadcast(first)).select("id", "v", "w", euclidean(F.col("v"), F.col("pivot")).alias("from")))
    seen = p.agg(F.count("*").alias("n"), F.min("from").alias("lo"), F.max("from").alias("hi")).first()
    # Wider cells than needed hold about a block each; the bit more than eps is for what rounding adds.
    width = max(eps * (1 + 1e-9), ((seen["hi"] or 0) - (seen["lo"] or 0)) * CROWD / max(seen["n"], 1)) or 1.0
    p = p.select("id", "v", "w", F.floor(F.col("from") / width).alias("cell"))

    def weigh(equal: bool, a: list[np.ndarray], b: list[np.ndarray]) -> dict:
        own, other = np.zeros(len(a[0])), np.zeros(len(b[0]))
        for s in range(0, len(own), 512):
            near = _within(a[1][s : s + 512], b[1], eps).astype(float)
            own[s : s + 512] = near @ b[2]
            other += a[2][s : s + 512] @ near
        if equal:  # every point is near itself
            return {"id": a[0], "near": own}
        return {"id": np.concatenate([a[0], b[0]]), "near": np.concatenate([own, other])}

    packs = _block_packs(p, eps, False)
    mass = _met(packs, packs, True, weigh, "id long, near double").groupBy("id").agg(F.sum("near").alias("near"))
    p = checkpointed(p.join(mass, "id").withColumn("core", F.col("near") >= min_pts).drop("near"))

    def link(equal: bool, a: list[np.ndarray], b: list[np.ndarray]) -> dict:
        if equal:
            return {"a": a[0], "b": a[0][a[3]]}
        (ka, la), (kb, lb) = (np.unique(x[3], return_inverse=True) for x in (a, b))
        hit = np.zeros((len(ka), len(kb)), bool)
        for s in range(0, len(la), 512):
            i, j = np.nonzero(_within(a[1][s : s + 512], b[1], eps))
            hit[la[s + i], lb[j]] = True
        rows, cols = _groups(hit)
        r, c = np.flatnonzero(rows >= 0), np.flatnonzero(cols >= 0)
        return {"a": np.concatenate([a[0][ka[r]], b[0][kb[c]]]), "b": a[0][ka[np.concatenate([rows[r], cols[c]])]]}

    cores = _block_packs(p.where("core"), eps, True)
    links = _met(cores, cores, True, link, "a long, b long").where("a <> b")
    comp = connected_components(links, "a", "b").withColumnRenamed("node", "id")
    core_cluster = checkpointed(p.where("core").select("id").join(comp, "id", "left").select("id", F.coalesce("component", "id").alias("cluster_id")))

    def nearest_core(equal: bool, a: list[np.ndarray], b: list[np.ndarray]) -> dict:
        found = [np.nonzero(_within(a[1][s : s + 512], b[1], eps)) for s in range(0, len(a[0]), 512)]
        i = np.concatenate([x + 512 * k for k, (x, _) in enumerate(found)])
        j = np.concatenate([y for _, y in found])
        return {"id": a[0][i], "distance": np.sqrt(((a[1][i] - b[1][j]) ** 2).sum(1)), "b": b[0][j]}

    # A point that is no core has few near ones, else it would be one.
    border = _met(_block_packs(p.where("NOT core"), eps, False), cores, False, nearest_core, "id long, distance double, b long")
    border = border.groupBy("id").agg(F.min(F.struct("distance", "b"))["b"].alias("b"))
    border = border.join(core_cluster.select(F.col("id").alias("b"), F.col("cluster_id").alias("border_cluster")), "b").select("id", "border_cluster")
    return p.select("id").join(core_cluster, "id", "left").join(border, "id", "left").select("id", F.coalesce("cluster_id", "border_cluster", F.lit(-1)).alias("cluster_id"))
