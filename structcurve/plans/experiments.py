"""The experiments on the given tables: encode, reduce, learn, measure."""

from __future__ import annotations

import time
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import encode, learn, lsi, metrics
from ..operators.descriptors import TARGETS, pair_targets
from ..operators.encode import EncodeConfig
from ..session import written
from ..sources.tables import atoms_from_lineitem, load, tokens

#: Published hyper-parameters: kept dimensions, learn rate, batch size by representation.
PUBLISHED = {"D1": (7, 3.74e-4, 37), "D2": (10, 7.11e-4, 52), "D3": (17, 1.03e-5, 72)}
NAMES = {"t_point": "point", "t_ffsum": "ffsum", "t_lattice": "lattice", "t_dispersion": "dispersion"}
CONFIGS = {"D1": EncodeConfig("atomic_number"), "D2": EncodeConfig("coordination", options={"cutoff": 10.0}), "D3": EncodeConfig("coulomb")}
#: The perceptron here has Adam steps and its own rate; the published rates belong to another optimiser.
MLP = learn.MlpConfig(hidden=(32,), rate=0.01, batch=64, epochs=60)


def targets_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``structure_id, fold, point, ffsum, lattice, dispersion`` of parts."""
    t = pair_targets(atoms_from_lineitem(spark, sf_dir, ids=True)).withColumnsRenamed(NAMES)
    return learn.kfold(t, 10)


def triplets_of(spark: SparkSession, sf_dir: str, rep: str = "D1", by: str = "part", config: EncodeConfig | None = None) -> DataFrame:
    config = config or CONFIGS[rep]
    atoms = atoms_from_lineitem(spark, sf_dir, by, ids=config.descriptor in ("coordination", "coulomb"))
    if config.descriptor != "coulomb":
        return encode.encode_structures(atoms, config)
    # the range of the descriptor is fitted before the encoding; the pair sums are made once for both
    s = written(encode.spherical_atoms(atoms, config).select("structure_id", "descriptor", "r", "polar", "azimuth"), "spherical")
    return encode.histogram(encode.indexed_atoms(s, config))


def reduced_of(triplets: DataFrame, k: int) -> tuple[DataFrame, lsi.LsiModel]:
    triplets = written(triplets, "triplets")
    model = lsi.fit_lsi(triplets, k)
    return lsi.reduce_structures(triplets, model, k, triplets), model


def learning_table(spark: SparkSession, sf_dir: str, rep: str, k: int | None = None, targets: DataFrame | None = None) -> DataFrame:
    """Targets (made anew without ``targets``) and vectors of the parts."""
    vectors, _ = reduced_of(triplets_of(spark, sf_dir, rep), k or PUBLISHED[rep][0])
    return written((targets if targets is not None else targets_of(spark, sf_dir)).join(vectors, "structure_id"), f"learn-{rep}")


def predictions(spark: SparkSession, sf_dir: str, rep: str, config: learn.MlpConfig = MLP, k: int | None = None, learner: str = "mlp", targets: DataFrame | None = None) -> DataFrame:
    table = learning_table(spark, sf_dir, rep, k, targets)
    return learn.cross_predict(table, list(NAMES.values()), config, learner).withColumn("rep", F.lit(rep))


def all_predictions(spark: SparkSession, sf_dir: str, learner: str = "mlp", targets: DataFrame | None = None) -> DataFrame:
    targets = written(targets_of(spark, sf_dir), "targets") if targets is None else targets
    runs = [predictions(spark, sf_dir, rep, learner=learner, targets=targets) for rep in CONFIGS]
    return written(runs[0].unionByName(runs[1]).unionByName(runs[2]), "predictions")


def error_table(spark: SparkSession, sf_dir: str, learner: str = "mlp") -> DataFrame:
    """``rep, split, target, mean, std``: fold means and deviations of the fraction error, the mean predictor first."""
    targets = written(targets_of(spark, sf_dir), "targets")
    p = all_predictions(spark, sf_dir, learner, targets)
    base = metrics.mean_predictions(targets, list(NAMES.values())).withColumn("rep", F.lit("mean"))
    errors = metrics.fraction_error(p.unionByName(base), ["rep", "split", "target", "fold"])
    return metrics.fold_summary(errors, ["rep", "split", "target"])


def recall_table(spark: SparkSession, sf_dir: str, pct: float = 15, learner: str = "mlp") -> DataFrame:
    """``rep, best, mean, std`` of the top recall of the point energy on test folds; the lattice order as baseline."""
    t = written(targets_of(spark, sf_dir), "targets")
    p = all_predictions(spark, sf_dir, learner, t).where("split = 'test' AND target = 'point'")
    runs = metrics.recall_at(p, pct, ["rep", "fold"])
    proxy = metrics.proxy_ranking(t, "lattice", "point", pct, ["fold"]).withColumn("rep", F.lit("lattice"))
    return metrics.recall_summary(runs.unionByName(proxy), ["rep"])


def k_curve(spark: SparkSession, sf_dir: str, ks: tuple[int, ...] = (1, 2, 3, 5, 7, 10, 15, 20, 30), rep: str = "D1") -> DataFrame:
    """``k, mean, std`` of the point energy's test error; the representation is reduced once, at the largest k."""
    table = learning_table(spark, sf_dir, rep, max(ks))
    p = learn.cross_predict(table, ["point"], replace(MLP, epochs=30), splits=("test",), ks=list(ks))
    return metrics.fold_summary(metrics.fraction_error(p, ["k", "fold"]), ["k"])


def violin(spark: SparkSession, sf_dir: str, rep: str = "D3") -> DataFrame:
    p = predictions(spark, sf_dir, rep).where("split = 'test'")
    both = p.select("target", F.lit("calc").alias("kind"), F.col("calc").alias("value")).union(p.select("target", F.lit("pred"), F.col("pred")))
    return metrics.violin_bins(both)


def search(spark: SparkSession, sf_dir: str, rep: str = "D1", n_trials: int = 12, method: str = "smbo", seed: int = 0) -> DataFrame:
    """Trials of the search over architecture, learn rate, batch and k; a round's models train side by side."""
    table = learning_table(spark, sf_dir, rep, 20)
    space = learn.Space({"hidden": ("choice", [(8,), (16,), (32,), (32, 16)]), "rate": ("loguniform", 1e-4, 1e-1), "batch": ("quniform", 16, 128, 1), "k": ("quniform", 2, 20, 1)})

    def objective(batch: list[dict]) -> list[float]:
        def one(i, ids, fold, x, y):
            import numpy as np
            import pyarrow as pa

            p, test = batch[i], fold == 8
            model = learn.train_local(x[~test, : p["k"]], y[~test], learn.MlpConfig(tuple(p["hidden"]), p["rate"], p["batch"], 30))
            loss = float(np.abs((model.predict(x[test, : p["k"]]) - y[test]) / y[test]).mean())
            yield pa.RecordBatch.from_pylist([{"trial": i, "loss": loss}], pa.schema([("trial", pa.int32()), ("loss", pa.float64())]))

        got = {r.trial: r.loss for r in learn.in_one_task_each(table.where("fold < 9"), len(batch), list(NAMES.values()), one, "trial int, loss double").collect()}
        return [got[i] for i in range(len(batch))]

    return learn.smbo_search(space, objective, n_trials, seed=seed, method=method, start=6, per_round=3).table(spark)


def speed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds for the pair-sum energies and for predicting them with a fitted model (reduced vectors to outputs), on suppliers."""
    atoms = written(atoms_from_lineitem(spark, sf_dir, "supplier", ids=True), "supplier-atoms")
    began = time.time()
    truth = written(pair_targets(atoms), "truth")
    direct = time.time() - began
    triplets = written(encode.encode_structures(atoms, CONFIGS["D1"]), "supplier-cells")
    model = lsi.fit_lsi(triplets, 7)
    vectors = written(lsi.reduce_structures(triplets, model, 7, triplets), "supplier-vectors")
    mlp = learn.train_distributed(truth.join(vectors, "structure_id"), list(TARGETS), replace(MLP, epochs=20, batch=None))
    began = time.time()
    n = learn.mlp_predict(vectors, mlp).select(F.sum(F.get("pred", F.lit(0)))).collect() and vectors.count()
    fast = time.time() - began
    return spark.createDataFrame([(n, float(direct), float(fast), float(direct / max(fast, 1e-9)))], "structures bigint, direct_s double, predict_s double, speedup double")


def _posed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The parts' spherical atoms, written once for configurations that differ in grid or curve alone."""
    return written(encode.spherical_atoms(atoms_from_lineitem(spark, sf_dir)).select("structure_id", "descriptor", "r", "polar", "azimuth").repartition("structure_id"), "posed")


def scaling(spark: SparkSession, sf_dir: str, bits: tuple[int, ...] = (3, 4, 6, 8)) -> DataFrame:
    """Non-zeros, vector length and seconds of a fit for growing resolutions over the same atoms."""
    rows = []
    posed = _posed(spark, sf_dir)
    for b in bits:
        t = written(encode.histogram(encode.indexed_atoms(posed, EncodeConfig(bits=b))), "scaling")
        began = time.time()
        model = lsi.fit_lsi(t, 5, "gram" if t.select("structure_id").distinct().count() <= lsi.GRAM_SIDE else "subspace")
        rows.append((b, float(2 ** (4 * b)), t.count(), model.cell_count(), float(time.time() - began)))
    return spark.createDataFrame(rows, "bits int, vector_length double, nonzeros bigint, cells bigint, seconds double")


def ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Curves, bits and radii: cells seen, non-zeros and collisions of each variant on parts."""
    out = None
    variants = [(f"bits={b}", EncodeConfig(bits=b)) for b in (2, 3, 4, 5, 6, 8)] + [(f"curve={c}", EncodeConfig(curve=c)) for c in ("hilbert", "peano", "rowmajor")] + [(f"radius={r}", EncodeConfig(radius=float(r))) for r in (30, 45)]
    posed = _posed(spark, sf_dir)
    for name, config in variants:
        t = written(encode.histogram(encode.indexed_atoms(posed, config)), "ablation")
        row = t.agg(F.count("*").alias("nonzeros"), F.countDistinct("cell").alias("cells"), F.sum("n").alias("atoms")).crossJoin(metrics.collision_rate(t).select("collision_rate")).withColumn("variant", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


def fit_on(spark: SparkSession, sf_dir: str, rep: str = "D1", folds: int = 3) -> DataFrame:
    """Error of the linear learner when idf and term vectors come from all rows and from the training folds only."""
    t = written(triplets_of(spark, sf_dir, rep), "fit-on")
    targets = written(learn.kfold(targets_of(spark, sf_dir).drop("fold"), folds), "fit-on-targets")
    every = None
    out = None
    for fold in range(folds):
        for how in ("all", "train"):
            ids = targets.where(F.col("fold") != fold).select("structure_id")
            if how == "train" or every is None:
                model = lsi.fit_lsi(t if how == "all" else t.join(ids, "structure_id", "left_semi"), 7)
                rows = written(targets.join(lsi.reduce_structures(t, model, 7, t), "structure_id"), "fit-on-table")
            if how == "all":
                rows = every = rows if every is None else every
            p = learn.cross_predict(rows.withColumn("fold", (F.col("fold") != fold).cast("int")), list(NAMES.values()), learner="ridge", folds=1, splits=("test",))
            e = metrics.fraction_error(p, ["target"]).withColumn("fold", F.lit(fold)).withColumn("fit_on", F.lit(how))
            out = e if out is None else out.unionByName(e)
    return metrics.fold_summary(out, ["fit_on", "target"])


def document_space(spark: SparkSession, sf_dir: str, k: int = 10, min_df: int = 5) -> tuple[DataFrame, lsi.LsiModel, DataFrame]:
    """(reduced documents, model, words with their cell numbers): indexing in its native setting."""
    words = tokens(load(spark, sf_dir, "documents"), "doc_id")
    cells = F.pmod(F.xxhash64("token"), F.lit(1 << 40))
    triplets = written(words.select("structure_id", cells.alias("cell"), "n").groupBy("structure_id", "cell").agg(F.sum("n").alias("n")), "doc-words")
    model = lsi.fit_lsi(triplets, k, min_df=min_df)
    return lsi.reduce_structures(triplets, model, k, triplets), model, triplets


def document_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Held-out error of labels predicted from reduced documents, against the mean."""
    vectors, _, _ = document_space(spark, sf_dir)
    labels = load(spark, sf_dir, "labels").select(F.col("doc_id").alias("structure_id"), (F.col("quality") + 1.0).alias("quality"))
    table = written(learn.kfold(labels.join(vectors, "structure_id"), 5), "doc-labels")
    p = learn.cross_predict(table, ["quality"], learner="ridge", folds=5, splits=("test",)).withColumn("model", F.lit("lsi"))
    base = metrics.mean_predictions(table, ["quality"]).withColumn("model", F.lit("mean"))
    return metrics.regression_report(p.unionByName(base), ["model"]).select("model", "mae", "rmse")


def benchmark_fold_in(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Test passages folded into the documents' space, with their nearest document by cosine."""
    from ..operators.joins import knn_exact
    from ..functions.vectors import norm

    vectors, model, _ = document_space(spark, sf_dir)
    words = tokens(load(spark, sf_dir, "benchmark"), "item_id").select("structure_id", F.pmod(F.xxhash64("token"), F.lit(1 << 40)).alias("cell"), "n")
    items = lsi.reduce_structures(words, model)
    unit = lambda d, name: d.where(norm("vec") > 0).select(F.col("structure_id").alias(name), F.transform("vec", lambda v: v / norm("vec")).alias("vec"))
    q = unit(items, "qid").withColumn("qid", -F.col("qid") - 1)
    return knn_exact(q, unit(vectors, "pid"), 1).select((-F.col("qid") - 1).alias("item_id"), F.col("pid").alias("doc_id"), "similarity")
