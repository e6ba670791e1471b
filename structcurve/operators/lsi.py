"""Latent semantic indexing on triplets: TF-IDF and a truncated SVD that touch non-zeros only."""

from __future__ import annotations

import json
import tempfile
import uuid
import warnings
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..session import written

#: Largest smaller side of the matrix that the exact Gram backend takes to the driver.
GRAM_SIDE = 4096
#: Largest number of terms whose vectors come to the driver and are sent to the tasks where structures are the smaller
#: side; the vectors of more terms stay rows.
BLOCK_TERMS = 1 << 20
#: Rows of the Gram matrix that come to the driver at once.
GRAM_ROWS = 256
#: Tasks that each add up a Gram matrix of their own.
GRAM_TASKS = 8
#: Bytes of the basis that the subspace backend keeps in the driver's memory.  A basis of fewer columns than BASIS_COLUMNS
#: restarts too often to converge: it is kept in a temporary file, of at most BASIS_FILE bytes (more only for some 2,900,000 names and up).
BASIS_BYTES, BASIS_COLUMNS, BASIS_FILE = 128 << 20, 44, 384 << 20
#: Bytes of the tasks' images that come to the driver in a pass, and the least and most tasks that make them.
IMAGE_BYTES, IMAGE_TASKS = 96 << 20, (4, 16)
#: Non-zeros in a packed row of the iteration (more only in a row of the matrix that has more), and those that a task
#: multiplies at once.  Packed rows are small because Parquet's writer holds 100 of them before it looks at their size.
PACKED, AT_ONCE = 1 << 15, 1 << 20


def term_frequency(triplets: DataFrame) -> DataFrame:
    """Adds ``tf``: a cell's share of its structure's atoms."""
    return triplets.withColumn("tf", F.col("n") / F.sum("n").over(Window.partitionBy("structure_id")))


def doc_frequency(triplets: DataFrame) -> DataFrame:
    """``cell, df``: in how many structures a cell occurs."""
    return triplets.groupBy("cell").agg(F.count("*").alias("df"))


def idf(frequency: DataFrame, structures: int) -> DataFrame:
    """Adds ``idf`` = ln(D / df), without smoothing."""
    return frequency.withColumn("idf", F.log(F.lit(float(structures)) / F.col("df")))


def tfidf(triplets: DataFrame, structures: int | None = None, weights: DataFrame | None = None) -> DataFrame:
    """``structure_id, cell, weight``; weight 0 (a cell of every structure) is dropped.

    ``weights`` (cell, idf) fixes the idf of a fit; cells that it lacks are dropped.  The planner
    broadcasts the cell side only under its size limit.
    """
    if weights is None:
        n = structures if structures is not None else triplets.select("structure_id").distinct().count()
        weights = idf(doc_frequency(triplets), n)
    return term_frequency(triplets).join(weights.select("cell", "idf"), "cell").where("idf > 0").select("structure_id", "cell", (F.col("tf") * F.col("idf")).alias("weight"))


@dataclass
class LsiModel:
    """Cells with idf and term vectors U, and the singular values.

    More than BLOCK_TERMS cells may be in ``terms`` (cell, idf, u) instead, and the three arrays are None.
    """

    cells: np.ndarray | None
    idf: np.ndarray | None
    u: np.ndarray | None
    sigma: np.ndarray
    passes: int = 0
    extra: dict = field(default_factory=dict)
    terms: DataFrame | None = None

    def cell_count(self) -> int:
        return len(self.cells) if self.terms is None else self.extra["cells"]

    def table(self, spark: SparkSession, k: int | None = None) -> DataFrame:
        import pyarrow as pa

        k = k or len(self.sigma)
        if self.terms is not None:
            return self.terms.select("cell", "idf", F.slice("u", 1, min(k, len(self.sigma))).alias("u"))
        k = min(k, self.u.shape[1])
        edges = pa.array(np.arange(len(self.cells) + 1) * k, pa.int32())
        u = pa.ListArray.from_arrays(edges, pa.array(self.u[:, :k].ravel()))
        return spark.createDataFrame(pa.table({"cell": pa.array(self.cells, pa.int64()), "idf": pa.array(self.idf), "u": u}), "cell bigint, idf double, u array<double>")

    def save(self, spark: SparkSession, path: str) -> None:
        self.table(spark).write.mode("overwrite").parquet(f"{path}/cells")
        spark.createDataFrame([(json.dumps(self.sigma.tolist()),)], "sigma string").write.mode("overwrite").json(f"{path}/sigma")

    @staticmethod
    def load(spark: SparkSession, path: str) -> LsiModel:
        rows = spark.read.parquet(f"{path}/cells")
        sigma = np.array(json.loads(spark.read.schema("sigma string").json(f"{path}/sigma").first().sigma))
        m = rows.count()
        if m > BLOCK_TERMS:
            return LsiModel(None, None, None, sigma, extra={"cells": m}, terms=rows)
        t = rows.orderBy("cell").toPandas()
        return LsiModel(t["cell"].to_numpy(), t["idf"].to_numpy(), np.array(t["u"].tolist()), sigma)


def _fixed_signs(u: np.ndarray) -> np.ndarray:
    """The entry of largest size in each column becomes positive."""
    if not u.size:
        return u
    return u * np.where(u[np.abs(u).argmax(axis=0), np.arange(u.shape[1])] < 0, -1.0, 1.0)


def fit_lsi(triplets: DataFrame, k: int, backend: str = "auto", structures: int | None = None, tolerance: float = 1e-5, passes: int = 240, min_df: int = 1) -> LsiModel:
    """TF-IDF and the k largest singular triples.

    ``gram``: exact, on the smaller side, at most GRAM_SIDE; ``subspace``: iteration on blocks, one
    pass over the non-zeros each; ``mllib``: the library's ARPACK for comparison.  ``auto`` takes gram where
    it fits.  ``min_df`` prunes rare cells (1 keeps all).  More than BLOCK_TERMS cells stay rows where the
    structures are fewer; the smaller side's vectors are always on the driver.
    """
    n = structures if structures is not None else triplets.select("structure_id").distinct().count()
    weights = idf(doc_frequency(triplets).where(F.col("df") >= min_df), n).persist()
    cells_df = weights.where("idf > 0")
    m = cells_df.count()
    by_cell, small = m <= n, min(n, m)
    if backend == "auto":
        backend = "gram" if small <= GRAM_SIDE else "subspace"
    if backend == "gram" and small > GRAM_SIDE:
        raise ValueError("the gram backend needs a side of at most 4096")
    k = min(k, small)
    if m > BLOCK_TERMS and not by_cell:
        weights.unpersist()
        if backend == "mllib":
            raise ValueError(f"{m} cells: the library's rows need all cells numbered on the driver")
        return _fit_many_cells(triplets, n, m, k, backend, tolerance, passes, min_df)
    table = cells_df.select("cell", "idf").toArrow().sort_by("cell")
    cells, idfs = table["cell"].to_numpy(), table["idf"].to_numpy()
    a = tfidf(triplets, weights=weights)
    if backend == "mllib":
        u, sigma, used = _svd_mllib(a, cells, k)
    elif backend == "gram":
        u, sigma, used = _svd_gram(a, cells, k, by_cell)
    elif by_cell:
        u, sigma, used = _svd_subspace(written(_packed(_tf_lists(triplets), cells, idfs), "packed"), m, k, tolerance, passes)
    else:
        names = _names(triplets)
        packed = written(_packed(_cell_lists(triplets, n, min_df), names), "packed")
        v, sigma, used = _svd_subspace(packed, len(names), k, tolerance, passes)
        rows = _term_rows(packed, v / np.where(sigma > 0, sigma, 1), n).toArrow()
        u = np.zeros((m, v.shape[1]))
        u[np.searchsorted(cells, rows["cell"].to_numpy())] = rows["u"].combine_chunks().flatten().to_numpy().reshape(-1, v.shape[1])
    weights.unpersist()
    return LsiModel(cells, idfs, _fixed_signs(u), sigma, used)


def _fit_many_cells(triplets: DataFrame, n: int, m: int, k: int, backend: str, tolerance: float, passes: int, min_df: int) -> LsiModel:
    """The fit on the structures' side; the term vectors are rows, made from the packed non-zeros wherever they are read."""
    lists, names = _cell_lists(triplets, n, min_df), _names(triplets)
    packed = written(_packed(lists, names), "packed")
    if backend == "gram":
        v, sigma, used = *_gram_vectors(lists.select("structure_id", "weight"), names, k), 2
    else:
        v, sigma, used = _svd_subspace(packed, len(names), k, tolerance, passes)
    v = v / np.where(sigma > 0, sigma, 1)
    entry = [F.get("u", F.lit(i)) for i in range(v.shape[1])]
    top = _term_rows(packed, v, n).agg(*(F.max_by(e, F.struct(F.abs(e), -F.col("cell"))).alias(f"c{i}") for i, e in enumerate(entry))).first()
    v = v * np.where(np.array(top) < 0, -1.0, 1.0)  # signs as in _fixed_signs
    return LsiModel(None, None, None, sigma, used, {"cells": m}, _term_rows(packed, v, n))


def _names(triplets: DataFrame) -> np.ndarray:
    return np.sort(triplets.select("structure_id").distinct().toArrow()["structure_id"].to_numpy())


def _svd_gram(a: DataFrame, cells: np.ndarray, k: int, by_cell: bool) -> tuple[np.ndarray, np.ndarray, int]:
    side, other = ("cell", "structure_id") if by_cell else ("structure_id", "cell")
    names = cells if by_cell else np.sort(a.select("structure_id").distinct().toArrow()["structure_id"].to_numpy())
    lists = a.groupBy(other).agg(F.collect_list(F.struct(side, "weight")).alias("e")).select(f"e.{side}", "e.weight")
    v, sigma = _gram_vectors(lists, names, k)
    if by_cell:
        return v, sigma, 1
    return _term_side(a, cells, names, v, sigma), sigma, 2


def _gram_vectors(lists: DataFrame, names: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The k best vectors on the side of ``names`` and their values, exact; lists hold names and weights."""
    parts = written(_gram_parts(lists.coalesce(GRAM_TASKS), names), "gram")
    g = np.zeros((len(names), len(names)))
    for lo in range(0, len(names), GRAM_ROWS):
        part = parts.where(F.col("i").between(lo, lo + GRAM_ROWS - 1)).toArrow()
        for i, v in zip(part["i"].to_pylist(), part["v"]):
            g[i, i:] += v.values.to_numpy()
    g = np.maximum(g, g.T)  # weights are positive, and below the diagonal there is 0 so far
    value, vector = np.linalg.eigh(g)
    del g
    sigma = np.sqrt(np.maximum(value[::-1][:k], 0))
    return vector[:, ::-1][:, :k], sigma


def _gram_parts(lists: DataFrame, names: np.ndarray) -> DataFrame:
    """``i, v``: row i of each task's own sum of outer products, from the diagonal on; lists hold names and weights."""
    import pyarrow as pa

    sent = lists.sparkSession.sparkContext.broadcast(names)

    def run(batches):
        known = sent.value
        total = np.zeros((len(known), len(known)))
        for batch in batches:
            for at, w in zip(batch.column(0), batch.column(1)):
                w = w.values.to_numpy()
                place = np.searchsorted(known, at.values.to_numpy())
                total[np.ix_(place, place)] += w[:, None] * w
        for lo in range(0, len(known), 64):
            rows = range(lo, min(lo + 64, len(known)))
            yield pa.RecordBatch.from_arrays([pa.array(list(rows), pa.int32()), pa.array([total[i, i:] for i in rows], pa.list_(pa.float64()))], ["i", "v"])

    return lists.mapInArrow(run, "i int, v array<double>")


def _multiplied(rows: DataFrame, names: np.ndarray, block: np.ndarray) -> DataFrame:
    """Key and ``vec`` of rows (key, names, weights): the weighted sum of the block's rows of these names.

    The block is sent once; names that it lacks are dropped, and so are rows without any other.
    """
    import pyarrow as pa

    key, chunk = rows.columns[0], 256
    sent = rows.sparkSession.sparkContext.broadcast((names, block))

    def run(batches):
        known, vectors = sent.value
        for batch in batches:
            for lo in range(0, batch.num_rows, chunk):
                keys, out = [], []
                for k, at, w in zip(*(batch.column(c).slice(lo, chunk) for c in range(3))):
                    at, w = at.values.to_numpy(), w.values.to_numpy()
                    place = np.minimum(np.searchsorted(known, at), len(known) - 1)
                    hit = known[place] == at
                    if hit.any():
                        keys.append(k.as_py())
                        out.append(w[hit] @ vectors[place[hit]])
                if keys:
                    flat = np.concatenate(out)
                    edges = pa.array(np.arange(len(keys) + 1) * vectors.shape[1], pa.int32())
                    yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.ListArray.from_arrays(edges, pa.array(flat))], [key, "vec"])

    return rows.mapInArrow(run, f"{key} bigint, vec array<double>")


def _by_structure(a: DataFrame) -> DataFrame:
    """Non-zeros as one row per structure."""
    e = F.sort_array(F.collect_list(F.struct("cell", "weight")))
    return a.groupBy("structure_id").agg(e.alias("e")).select("structure_id", F.col("e.cell").alias("cells"), F.col("e.weight").alias("weights"))


def _tf_lists(triplets: DataFrame) -> DataFrame:
    """``structure_id, cell, tf``: one row per structure, from one shuffle."""
    rows = term_frequency(triplets).groupBy("structure_id").agg(F.collect_list(F.struct("cell", "tf")).alias("e"))
    return rows.select("structure_id", "e.cell", "e.tf")


def _cell_lists(triplets: DataFrame, structures: int, min_df: int) -> DataFrame:
    """``cell, structure_id, weight``: the weights of :func:`tfidf` as one row per cell, whose length is its frequency: no join."""
    rows = term_frequency(triplets).groupBy("cell").agg(F.collect_list(F.struct("structure_id", "tf")).alias("e"))
    rows = idf(rows.withColumn("df", F.size("e")).where(F.col("df") >= min_df), structures).where("idf > 0")
    return rows.select("cell", "e.structure_id", F.transform("e.tf", lambda t: t * F.col("idf")).alias("weight"))


def _packed(lists: DataFrame, names: np.ndarray, factors: np.ndarray | None = None) -> DataFrame:
    """``sizes, places, weights, keys``: rows (key, names, weights) as bytes, many rows in one, names as places among the given ones.

    With ``factors``, one for each name, weights are multiplied by them and other names are dropped.
    """
    import pyarrow as pa

    sent = lists.sparkSession.sparkContext.broadcast((names, factors))

    def run(batches):
        known, factors = sent.value
        for batch in batches:
            keys, lists, values = batch.column(0).to_numpy(), batch.column(1), batch.column(2)
            sizes = np.diff(lists.offsets.to_numpy()).astype(np.int32)
            at, w = lists.flatten().to_numpy(), values.flatten().to_numpy()
            place = np.searchsorted(known, at).astype(np.int32)
            if factors is not None:
                place = np.minimum(place, len(known) - 1)
                hit = known[place] == at
                sizes = np.bincount(np.repeat(np.arange(len(sizes)), sizes)[hit], minlength=len(sizes)).astype(np.int32)
                place, w = place[hit], w[hit] * factors[place[hit]]
            ends = np.cumsum(sizes, dtype=np.int64)
            lo = start = 0
            while lo < len(sizes):
                hi = max(lo + 1, int(np.searchsorted(ends, start + PACKED, side="right")))
                end = int(ends[hi - 1])
                parts = sizes[lo:hi], place[start:end], w[start:end], keys[lo:hi]
                yield pa.RecordBatch.from_arrays([pa.array([p.tobytes()], pa.binary()) for p in parts], ["sizes", "places", "weights", "keys"])
                lo, start = hi, end

    return lists.mapInArrow(run, "sizes binary, places binary, weights binary, keys binary")


def _term_rows(packed: DataFrame, v: np.ndarray, structures: int) -> DataFrame:
    """``cell, idf, u`` for the rows of :func:`_packed`, a cell each: the weighted sum of the sent rows of v, one for each name."""
    import pyarrow as pa

    sent = packed.sparkSession.sparkContext.broadcast(np.ascontiguousarray(v.T))

    def run(batches):
        block = sent.value
        for batch in batches:
            for row in zip(*(batch.column(i) for i in range(4))):
                sizes, at, w, keys = (np.frombuffer(x.as_buffer(), kind) for x, kind in zip(row, (np.int32, np.int32, np.float64, np.int64)))
                own = np.repeat(np.arange(len(sizes)), sizes)
                u = np.stack([np.bincount(own, w * column[at], len(sizes)) for column in block], axis=1)
                edges = pa.array(np.arange(len(sizes) + 1) * len(block), pa.int32())
                yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(np.log(structures / sizes)), pa.ListArray.from_arrays(edges, pa.array(u.ravel()))], ["cell", "idf", "u"])

    return packed.mapInArrow(run, "cell bigint, idf double, u array<double>")


def _image(packed: DataFrame, q: np.ndarray) -> np.ndarray:
    """A^T (A q) for the rows A of :func:`_packed`: the block is sent, each task returns the sum over its rows."""
    import pyarrow as pa

    columns = np.ascontiguousarray(q.T)
    sent = packed.sparkSession.sparkContext.broadcast(columns)

    def run(batches):
        block = sent.value
        total = np.zeros_like(block)

        def add(held):
            sizes, at, w = (np.concatenate(x) for x in zip(*held))
            own = np.repeat(np.arange(len(sizes)), sizes)
            for c, column in enumerate(block):
                projected = np.bincount(own, w * column[at], len(sizes))
                total[c] += np.bincount(at, w * projected[own], block.shape[1])

        held, size = [], 0
        for batch in batches:
            for row in zip(*(batch.column(i) for i in range(3))):
                held.append([np.frombuffer(v.as_buffer(), kind) for v, kind in zip(row, (np.int32, np.int32, np.float64))])
                size += len(held[-1][1])
                if size >= AT_ONCE:
                    add(held)
                    held, size = [], 0
        if held:
            add(held)
        yield pa.RecordBatch.from_arrays([pa.array([r.tobytes()], pa.binary()) for r in [total]], ["v"])

    tasks = min(IMAGE_TASKS[1], max(IMAGE_TASKS[0], IMAGE_BYTES // columns.nbytes))
    y = np.zeros_like(columns)
    for v in packed.select("sizes", "places", "weights").coalesce(tasks).mapInArrow(run, "v binary").toArrow()["v"]:
        y += np.frombuffer(v.as_buffer()).reshape(y.shape)
    sent.destroy()
    return np.ascontiguousarray(y.T)


def _room(m: int, columns: int) -> np.ndarray:
    """Zeros of this shape, column by column; above BASIS_BYTES in a file without a name, which goes with the array."""
    if 8 * m * columns <= BASIS_BYTES:
        return np.zeros((m, columns), order="F")
    with tempfile.TemporaryFile() as f:
        return np.asarray(np.memmap(f, np.float64, "w+", shape=(m, columns), order="F"))


def _svd_subspace(packed: DataFrame, m: int, k: int, tolerance: float, passes: int) -> tuple[np.ndarray, np.ndarray, int]:
    """The best vectors of the space that a block and its images under A^T A span, for packed rows A over m places.

    Each pass multiplies one block; the basis is kept orthonormal on the driver and restarted from the best vectors
    where it would outgrow its room.  Ends when the k vectors' residuals are at most ``tolerance`` of the largest value.
    """
    width = min(m, k + 10, max(4, BASIS_BYTES // (32 * m)))
    most = min(m, max(BASIS_BYTES // (8 * m), min(BASIS_COLUMNS, BASIS_FILE // (8 * m)), k + 3 * width))
    q = np.linalg.qr(np.random.default_rng(7).normal(size=(m, width)))[0]
    room, inner, used = _room(m, most), np.zeros((0, 0)), 0
    for used in range(1, passes + 1):
        before = len(inner)
        room[:, before : before + q.shape[1]] = q
        basis = room[:, : before + q.shape[1]]
        y = _image(packed, q)
        shares = basis.T @ y
        inner = np.pad(inner, (0, basis.shape[1] - before))
        inner[:, before:], inner[before:] = shares, shares.T
        y -= basis @ shares
        y -= basis @ (basis.T @ y)
        value, rotation = np.linalg.eigh((inner + inner.T) / 2)
        value, rotation = value[::-1], rotation[:, ::-1]
        u, size, mix = np.linalg.svd(y, full_matrices=False)
        residuals = np.linalg.norm(size[:, None] * mix @ rotation[before:, :k], axis=0)
        kept = size > 1e-11 * max(value[0], 1e-300)
        if (len(residuals) == k and residuals.max(initial=0.0) <= tolerance * value[0]) or not kept.any():
            break
        u = u[:, kept][:, : m - basis.shape[1]]
        if not u.size:
            break
        q = np.linalg.qr(u - basis @ (basis.T @ u))[0]
        if basis.shape[1] + q.shape[1] > most:
            kept = min(k + width, most - q.shape[1], basis.shape[1])
            for lo in range(0, m, 65536):
                basis[lo : lo + 65536, :kept] = basis[lo : lo + 65536] @ rotation[:, :kept]
            basis, inner, rotation = basis[:, :kept], np.diag(value[:kept]), np.eye(kept)
    else:
        warnings.warn(f"no convergence in {passes} passes: residual {residuals.max(initial=0.0):.3g} of {value[0]:.3g}", stacklevel=2)
    sigma = np.sqrt(np.maximum(value[:k], 0))
    return basis @ rotation[:, :k], sigma, used


def _term_side(a: DataFrame, cells: np.ndarray, names: np.ndarray, v: np.ndarray, sigma: np.ndarray) -> np.ndarray:
    """U = A V / sigma, summed over the non-zeros; V has a row for each of ``names``, the structures."""
    rows = a.groupBy("cell").agg(F.collect_list(F.struct("structure_id", "weight")).alias("e"))
    u = _multiplied(rows.select("cell", "e.structure_id", "e.weight"), names, v / np.where(sigma > 0, sigma, 1)).toArrow()
    out = np.zeros((len(cells), v.shape[1]))
    out[np.searchsorted(cells, u["cell"].to_numpy())] = u["vec"].combine_chunks().flatten().to_numpy().reshape(-1, v.shape[1])
    return out


def _svd_mllib(a: DataFrame, cells: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, int]:
    from pyspark.mllib.linalg import Vectors
    from pyspark.mllib.linalg.distributed import RowMatrix

    size, names = len(cells), {int(c): i for i, c in enumerate(cells)}
    rows = _by_structure(a).rdd.map(lambda r: Vectors.sparse(size, sorted((names[c], w) for c, w in zip(r.cells, r.weights))))
    found = RowMatrix(rows, numCols=size).computeSVD(k)
    return found.V.toArray(), np.array(found.s.toArray()), -1


def reduce_structures(triplets: DataFrame, model: LsiModel, k: int | None = None, structures: DataFrame | None = None, scale: str = "svt") -> DataFrame:
    """``structure_id, vec``: U^T a' (that is S V^T), or V^T alone with ``scale='vt'``.

    Unseen cells are dropped; structures without any known cell get zeros if ``structures`` lists them.
    The tasks multiply by the sent term vectors, which never become rows on the driver; a model's ``terms`` are joined.
    """
    k = min(k or len(model.sigma), len(model.sigma))
    if model.terms is not None:
        out = _joined(triplets, model.terms, k, model.sigma[:k] if scale == "vt" else None)
        return out if structures is None else _all_of(structures, out, k)
    size = model.idf[:, None] if scale == "svt" else model.idf[:, None] / np.where(model.sigma[:k] > 0, model.sigma[:k], np.inf)
    out = _multiplied(_tf_lists(triplets), model.cells, model.u[:, :k] * size)
    return out if structures is None else _all_of(structures, out, k)


def _joined(triplets: DataFrame, terms: DataFrame, k: int, sigma: np.ndarray | None) -> DataFrame:
    """``structure_id, vec``: the sums of tf * idf * u over the known cells, over ``sigma`` where that is given and not 0."""
    by = [1.0] * k if sigma is None else [1 / float(s) if s > 0 else 0.0 for s in sigma]
    rows = term_frequency(triplets).join(terms, "cell").withColumn("weight", F.col("tf") * F.col("idf"))
    total = rows.groupBy("structure_id").agg(*(F.sum(F.col("weight") * F.get("u", F.lit(i))).alias(f"s{i}") for i in range(k)))
    return total.select("structure_id", F.array(*(F.col(f"s{i}") * F.lit(by[i]) for i in range(k))).alias("vec"))


def _all_of(structures: DataFrame, vectors: DataFrame, k: int) -> DataFrame:
    """The vectors of all structures, zeros where there is none."""
    every = structures.select("structure_id").distinct()
    return every.join(vectors, "structure_id", "left").select("structure_id", F.coalesce("vec", F.array_repeat(F.lit(0.0), k)).alias("vec"))


def unseen_cells(triplets: DataFrame, model: LsiModel) -> DataFrame:
    return triplets.join(model.table(triplets.sparkSession, 1).select("cell"), "cell", "left_anti").groupBy("structure_id").agg(F.sum("n").alias("unseen"))


def spectrum(model: LsiModel, spark: SparkSession) -> DataFrame:
    """``dim, sigma, gradient``: central differences, one-sided at the ends."""
    rows = spark.createDataFrame([(i + 1, float(s)) for i, s in enumerate(model.sigma)], "dim int, sigma double")
    return gradient(rows)


def gradient(rows: DataFrame) -> DataFrame:
    order = Window.orderBy("dim")  # one row per kept dimension
    up, down = F.lead("sigma").over(order), F.lag("sigma").over(order)
    return rows.withColumn("gradient", F.when(down.isNull(), up - F.col("sigma")).when(up.isNull(), F.col("sigma") - down).otherwise((up - down) / 2))


def choose_k(sigma: np.ndarray, rule: str = "slope", threshold: float = -0.001, relative: bool = False, energy: float = 0.9) -> int:
    """Dimensions kept: all before the slope first rises to the threshold, or those that hold a share of the energy."""
    s = np.asarray(sigma, float)
    if rule == "energy":
        return int(np.searchsorted(np.cumsum(s**2) / max((s**2).sum(), 1e-300), energy) + 1)
    if len(s) < 2:
        return len(s)
    g = np.gradient(s / s[0] if relative else s)
    flat = np.nonzero(g >= threshold)[0]
    return max(1, int(flat[0])) if len(flat) else len(s)


def new_path(base: str) -> str:
    return f"{base.rstrip('/')}/lsi-{uuid.uuid4().hex}"
