"""Every method, baseline, measure, workload and operator as a query (spark, sf_dir) -> DataFrame."""

from __future__ import annotations

import math
import uuid
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import features, layout
from ..functions.vectors import dot, norm, sqdist
from ..operators import align, anchors, diagnostics, graph, grid, kmeans, metrics, numeric, partymap, privacy, protocol
from ..operators import spectral as spectral_ops
from ..operators.grid import GridSpec, even_columns, split_grid
from ..session import materialise, shared_dir
from ..sources.tables import hash_sample, load, load_model, load_text, save_model, write_blocks
from ..streaming import scoring
from . import baselines, sqlapi, workloads
from .estimator import GridClusterer
from .pipeline import grid_cluster

REGISTRY: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
DIGITS = 6


def query(f: Callable[[SparkSession, str], DataFrame]):
    REGISTRY[f.__name__] = f
    return f


def r(c, digits: int = DIGITS):
    """Rounded, and never a negative zero."""
    return F.round(c, digits) + F.lit(0.0)


# -- points that several queries share -------------------------------------------------------------------------


#: Components of the given vectors; all are used.
DIMS = 64


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    dims = DIMS
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("row_id"), F.array(*(F.col("embedding")[i].cast("double") for i in range(dims))).alias("z"), "label")


#: Fixed centers for queries whose result must not depend on a search.
CENTERS = np.array([[round(0.1 * math.cos(1.3 * k + 0.7 * i), 3) for i in range(DIMS)] for k in range(3)])


def assigned(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = vectors(spark, sf_dir)
    return kmeans.assign(v, CENTERS, distance="dist").withColumn("truth", F.pmod("label", F.lit(3)))


def lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Narrow measures of order lines, ten row groups."""
    return workloads.lineitem_numeric(spark, sf_dir)


def small_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_linenumber", "l_quantity", "l_discount", "l_tax", "l_shipdate"])
    return x.select(F.col("l_orderkey").alias("row_id"), F.pmod("l_orderkey", F.lit(4)).cast("int").alias("row_grp"), F.array("l_quantity", F.col("l_discount") * 100, F.col("l_tax") * 100, F.month("l_shipdate").cast("double")).alias("feats"))


def parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two column parties of two features each, row groups by key."""
    x = load(spark, sf_dir, "part", ["p_partkey", "p_size", "p_retailprice"])
    return x.select(F.col("p_partkey").alias("row_id"), F.pmod("p_partkey", F.lit(2)).cast("int").alias("row_grp"), F.array(F.col("p_size").cast("double"), F.col("p_retailprice") / 100, F.pmod("p_partkey", F.lit(13)).cast("double"), F.pmod("p_partkey", F.lit(7)) + F.col("p_size") / 10).alias("feats"))


TWO_BY_TWO = GridSpec(((0, 1), (2, 3)))

# -- lattice, anchors, maps, codes -----------------------------------------------------------------------------


@query
def grid_blocks_card(spark, sf_dir):
    """Rows and feature means of every block of the customers' lattice."""
    p = workloads.customer_orders(spark, sf_dir)
    long = p.select("row_grp", F.posexplode("feats").alias("pos", "val")).withColumn("col_grp", F.when(F.col("pos") < 2, 0).otherwise(1))
    return long.groupBy("row_grp", "col_grp", "pos").agg(F.count(F.lit(1)).alias("n"), r(F.avg("val"), 4).alias("mean"))


@query
def feature_bounds(spark, sf_dir):
    b = numeric.column_bounds(lines(spark, sf_dir), 5)
    return spark.createDataFrame([(i, lo, hi) for i, (lo, hi) in enumerate(b)], "pos int, lo double, hi double")


@query
def anchor_uniform_rows(spark, sf_dir):
    a = anchors.anchor_uniform(spark, numeric.column_bounds(parts(spark, sf_dir), 4), 300, seed=5)
    return a.select("anchor_id", F.posexplode("feats").alias("pos", "val")).withColumn("val", r("val"))


@query
def anchor_lowrank_rows(spark, sf_dir):
    return anchors.anchor_lowrank(spark, parts(spark, sf_dir), 200, 2, seed=5)


@query
def anchor_mix_rows(spark, sf_dir):
    return anchors.anchor_mix(parts(spark, sf_dir), 200, seed=5)


@query
def anchor_public_rows(spark, sf_dir):
    bench = load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("row_id"), F.array(*features.letter_shares(F.col("text"))).alias("feats"))
    return anchors.anchor_from(bench).select("anchor_id", *(r(F.col("feats")[i]).alias(f"f{i}") for i in range(10)))


def _planted(p: DataFrame) -> DataFrame:
    return p.select("row_id", "truth", *(r(F.col("feats")[i], 5).alias(f"f{i}") for i in range(6)))


@query
def planted_blobs_rows(spark, sf_dir):
    return _planted(workloads.planted_blobs(spark, sf_dir))


@query
def planted_rings_rows(spark, sf_dir):
    return _planted(workloads.planted_rings(spark, sf_dir))


@query
def planted_skew_groups(spark, sf_dir):
    return workloads.planted_blobs(spark, sf_dir, "skew").groupBy("row_grp", "truth").agg(F.count(F.lit(1)).alias("n"))


@query
def equal_groups_sizes(spark, sf_dir):
    """Ten random row groups whose sizes differ by one at most."""
    p = load(spark, sf_dir, "orders", ["o_orderkey"]).select(F.col("o_orderkey").alias("row_id"))
    return grid.equal_groups(p, 10).groupBy("row_grp").agg(F.count(F.lit(1)).alias("n"))


@query
def standardised_block(spark, sf_dir):
    c = load(spark, sf_dir, "customer", ["c_custkey", "c_nationkey", "c_acctbal"])
    return features.standardise(c, ["c_acctbal"], by="c_nationkey").select("c_custkey", r("c_acctbal").alias("z"))


@query
def block_covariance(spark, sf_dir):
    """Covariances inside each block, from the one-pass moments."""
    m = numeric.moments(small_lines(spark, sf_dir), TWO_BY_TWO.col_groups)
    rows = [(i, j, a, b, n, float(cross[a, b] / n)) for (i, j), (n, _, cross) in m.items() for a in range(2) for b in range(2)]
    return spark.createDataFrame(rows, "row_grp int, col_grp int, a int, b int, n long, cov double").withColumn("cov", r("cov", 4))


@query
def block_gram(spark, sf_dir):
    g = numeric.gram(small_lines(spark, sf_dir), "feats", with_one=True)
    return spark.createDataFrame([(a, b, float(g[a, b])) for a in range(5) for b in range(5)], "a int, b int, dot double").withColumn("dot", r("dot", 3))


@query
def pca2_closed_form(spark, sf_dir):
    """Means and leading components of two-feature parties, one component each."""
    maps = partymap.fit_pca_maps(parts(spark, sf_dir), TWO_BY_TWO, scale=False)
    rows = [(i, j, a, float(m.mean[a]), float(m.proj[a, 0])) for (i, j), m in maps.items() for a in range(2)]
    return spark.createDataFrame(rows, "row_grp int, col_grp int, a int, mean double, proj double").select("row_grp", "col_grp", "a", r("mean").alias("mean"), r("proj", 5).alias("proj"))


@query
def encode_rows(spark, sf_dir):
    p = parts(spark, sf_dir)
    codes = partymap.encode(p, TWO_BY_TWO, partymap.fit_pca_maps(p, TWO_BY_TWO, scale=False))
    return codes.select("row_id", "row_grp", "col_grp", r(F.col("code")[0], 5).alias("code"))


@query
def concat_codes(spark, sf_dir):
    p = parts(spark, sf_dir)
    codes = align.concat_codes(partymap.encode(p, TWO_BY_TWO, partymap.fit_pca_maps(p, TWO_BY_TWO, scale=False)))
    return codes.select("row_id", r(F.col("code")[0], 5).alias("c0"), r(F.col("code")[1], 5).alias("c1"))


def _anchor_codes(spark, sf_dir, **options):
    p = parts(spark, sf_dir)
    maps = partymap.fit_pca_maps(p, TWO_BY_TWO, **options)
    shared = anchors.anchor_uniform(spark, numeric.column_bounds(p, 4), 300, seed=5)
    return partymap.encode_anchors(shared, TWO_BY_TWO, maps), maps


@query
def anchor_block_gram(spark, sf_dir):
    """Cross products of the shared anchors themselves, a constant column included."""
    a = anchors.anchor_uniform(spark, numeric.column_bounds(parts(spark, sf_dir), 4), 300, seed=5)
    g = numeric.gram(a, "feats", with_one=True)
    return spark.createDataFrame([(i, j, float(g[i, j])) for i in range(5) for j in range(5)], "a int, b int, dot double").withColumn("dot", r("dot", 3))


@query
def alignment_residual_full_width(spark, sf_dir):
    """Without reduction affine aligners bring all groups' anchors together."""
    codes, _ = _anchor_codes(spark, sf_dir, width=2, allow_full=True)
    found = align.fit_aligner(codes, "affine")
    return spark.createDataFrame([(0, 1, align.anchor_difference(codes, found, 0, 1))], "a int, b int, residual double").withColumn("residual", r("residual"))


@query
def alignment_residuals(spark, sf_dir):
    """Linear against affine aligners on reduced codes."""
    codes, _ = _anchor_codes(spark, sf_dir, scale=True)
    rows = [(kind, solver, align.fit_aligner(codes, kind, solver=solver).residual(0, 1)) for kind in ("linear", "affine") for solver in ("gram", "tsqr")]
    return spark.createDataFrame(rows, "kind string, solver string, residual double").select("kind", "solver", (F.col("residual") > 1e-3).alias("left_over"))


@query
def exactness(spark, sf_dir):
    """Whether the conditions for exact affine alignment hold, at full and at reduced width."""
    rows = []
    from ..operators.exactness import block_projection, exactness_report

    for width, full in (("minus1", False), (2, True)):
        codes, maps = _anchor_codes(spark, sf_dir, width=width, allow_full=full)
        wide, _ = align.anchor_rows(codes)
        a = np.array([x["codes"] for x in wide.orderBy("anchor_id").collect()])
        half = a.shape[1] // 2
        report = exactness_report({i: block_projection(TWO_BY_TWO, maps, i)[0] for i in (0, 1)}, {0: a[:, :half], 1: a[:, half:]})
        rows.append((str(width), report.equal_ranges, report.full_rank, report.affine_exact))
    return spark.createDataFrame(rows, "width string, equal_ranges boolean, full_rank boolean, affine_exact boolean")


@query
def leak_probe(spark, sf_dir):
    p = parts(spark, sf_dir)
    lost = privacy.leak_probe(p, TWO_BY_TWO, partymap.fit_pca_maps(p, TWO_BY_TWO, scale=False))
    return spark.createDataFrame([(i, j, v) for (i, j), v in lost.items()], "row_grp int, col_grp int, lost double").withColumn("lost", r("lost", 5))


@query
def comm_volume(spark, sf_dir):
    return protocol.comm_volume(parts(spark, sf_dir), {(i, j): 1 for i in (0, 1) for j in (0, 1)}, 300, 3, 2)


# -- k-means ---------------------------------------------------------------------------------------------------


@query
def nearest_center(spark, sf_dir):
    return assigned(spark, sf_dir).select("row_id", "pred", r("dist").alias("dist"))


@query
def nearest_center_sql(spark, sf_dir):
    """The same through the registered SQL function."""
    sqlapi.register_all(spark)
    vectors(spark, sf_dir).createOrReplaceTempView("gridcluster_points")
    text = ", ".join("array(" + ", ".join(f"{x}D" for x in c) + ")" for c in CENTERS.tolist())
    return spark.sql(f"SELECT row_id, nearest_center(z, array({text})) AS pred FROM gridcluster_points")


def _lloyd(spark, sf_dir, passes):
    v = vectors(spark, sf_dir)
    found = kmeans.lloyd(v, {0: [kmeans.seed_fixed(v, 3)]}, passes)[0][0]
    return spark.createDataFrame([(k, i, float(x)) for k, c in enumerate(found.centers) for i, x in enumerate(c)], "cluster int, pos int, val double").withColumn("val", r("val"))


@query
def lloyd_1(spark, sf_dir):
    return _lloyd(spark, sf_dir, 1)


@query
def lloyd_5(spark, sf_dir):
    return _lloyd(spark, sf_dir, 5)


@query
def dsq_weights(spark, sf_dir):
    """Squared distance to the nearest of the first three rows: the weights of the next draw."""
    v = vectors(spark, sf_dir)
    return kmeans.assign(v, kmeans.seed_fixed(v, 3), distance="d").select("row_id", r("d").alias("w"))


@query
def pairwise_center(spark, sf_dir):
    """Labels by a join with the table of centers."""
    return kmeans.pairwise_assign(vectors(spark, sf_dir), CENTERS).select("row_id", "pred", r("dist").alias("dist"))


@query
def cumulative_draw(spark, sf_dir):
    """Rows drawn at given shares of the running sum of order prices."""
    o = load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]).select(F.col("o_orderkey").alias("row_id"), F.col("o_totalprice").alias("w"))
    shares = [0.05, 0.25, 0.5, 0.75, 0.95]
    return spark.createDataFrame(list(zip(shares, kmeans.cumulative_draw(o, shares))), "share double, row_id long")


@query
def seed_farthest(spark, sf_dir):
    c = kmeans.seed_fixed(vectors(spark, sf_dir), 4, "farthest")
    return spark.createDataFrame([(i, float(x[0]), float(x[1])) for i, x in enumerate(c)], "draw int, z0 double, z1 double").select("draw", r("z0").alias("z0"), r("z1").alias("z1"))


@query
def seed_dsq(spark, sf_dir):
    c = kmeans.seed_dsq(vectors(spark, sf_dir), 5, seed=3)[0][0]
    return spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(c)], "draw int, center array<double>")


@query
def seed_parallel(spark, sf_dir):
    c = kmeans.seed_parallel(vectors(spark, sf_dir), 5, seed=3)
    return spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(c)], "draw int, center array<double>")


@query
def inertia_by_cluster(spark, sf_dir):
    return assigned(spark, sf_dir).groupBy("pred").agg(F.count(F.lit(1)).alias("n"), r(F.avg("dist")).alias("inertia"))


@query
def fed_merge_round(spark, sf_dir):
    """Parties' centers merged by their counts."""
    a = assigned(spark, sf_dir).withColumn("party", F.pmod("row_id", F.lit(10)))
    local = a.groupBy("party", "pred").agg(F.count(F.lit(1)).alias("n"), F.avg(F.col("z")[0]).alias("c0"), F.avg(F.col("z")[1]).alias("c1"))
    return local.groupBy("pred").agg(r(F.sum(F.col("n") * F.col("c0")) / F.sum("n")).alias("c0"), r(F.sum(F.col("n") * F.col("c1")) / F.sum("n")).alias("c1"))


# -- graphs ----------------------------------------------------------------------------------------------------


def _edges(spark, sf_dir):
    return graph.knn_graph(vectors(spark, sf_dir), q=5)


@query
def knn_edges(spark, sf_dir):
    return _edges(spark, sf_dir).select("src", "dst", r("dist").alias("dist"))


@query
def knn_edges_lsh(spark, sf_dir):
    return graph.knn_graph(vectors(spark, sf_dir), q=5, method="lsh")


@query
def knn_symmetric(spark, sf_dir):
    return graph.symmetrise(_edges(spark, sf_dir))


@query
def knn_union(spark, sf_dir):
    return graph.symmetrise(_edges(spark, sf_dir), "union")


@query
def knn_mutual(spark, sf_dir):
    return graph.symmetrise(_edges(spark, sf_dir), "mutual")


@query
def knn_degree(spark, sf_dir):
    return graph.degree(graph.symmetrise(_edges(spark, sf_dir)))


@query
def laplacian_plain(spark, sf_dir):
    return graph.laplacian(graph.symmetrise(_edges(spark, sf_dir)))


@query
def laplacian_sym(spark, sf_dir):
    return graph.laplacian(graph.symmetrise(_edges(spark, sf_dir)), "sym").withColumn("val", r("val"))


@query
def radius_edges(spark, sf_dir):
    return graph.radius_edges(vectors(spark, sf_dir), 1.0).select("src", "dst", r("dist").alias("dist"))


@query
def spectral_embedding(spark, sf_dir):
    """Least eigenvalues of the normalised Laplacian of the language graph, dense and distributed."""
    p = workloads.text_language(spark, sf_dir).select("row_id", F.col("feats").alias("z"))
    e = materialise(spark, graph.symmetrise(graph.knn_graph(p, 10)), "edges")
    _, dense = spectral_ops.embed(spark, e, 4)
    return spark.createDataFrame([(i, float(v)) for i, v in enumerate(dense)], "number int, eigenvalue double")


@query
def power_iteration(spark, sf_dir):
    p = workloads.text_language(spark, sf_dir).select("row_id", F.col("feats").alias("z"))
    return spectral_ops.power_iteration(graph.symmetrise(graph.knn_graph(p, 10)), 4)


# -- measures --------------------------------------------------------------------------------------------------


@query
def contingency(spark, sf_dir):
    return metrics.contingency(assigned(spark, sf_dir))


@query
def contingency_cube(spark, sf_dir):
    return metrics.margins(assigned(spark, sf_dir))


@query
def ari(spark, sf_dir):
    return metrics.ari_rows(assigned(spark, sf_dir)).select(r("ari").alias("ari"))


@query
def nmi(spark, sf_dir):
    return metrics.nmi_rows(assigned(spark, sf_dir)).select(r("nmi").alias("nmi"))


@query
def acc_k3(spark, sf_dir):
    u = metrics.table_of(metrics.contingency(assigned(spark, sf_dir)))
    return spark.createDataFrame([(metrics.acc(u),)], "acc double").select(r("acc").alias("acc"))


@query
def ari_grouped_udf(spark, sf_dir):
    """The same index as a grouped aggregate in SQL, by hash bucket."""
    sqlapi.register_all(spark)
    a = assigned(spark, sf_dir).withColumn("b", F.pmod("row_id", F.lit(4)))
    a.select("b", "truth", "pred").createOrReplaceTempView("gridcluster_labels")
    return spark.sql("SELECT b, round(ari_agg(truth, pred), 6) + 0.0 AS ari FROM gridcluster_labels GROUP BY b")


@query
def anchor_rows_udtf(spark, sf_dir):
    """Fifty anchors a nation by the registered table function, uniform in the ranges of its customers' balances and keys."""
    sqlapi.register_all(spark)
    load(spark, sf_dir, "customer", ["c_nationkey", "c_acctbal", "c_custkey"]).createOrReplaceTempView("gridcluster_customers")
    bounds = "SELECT c_nationkey, " + ", ".join(f"array(CAST({f}(c_acctbal) AS DOUBLE), CAST({f}(c_custkey) AS DOUBLE)) AS {n}" for f, n in (("min", "lows"), ("max", "highs"))) + " FROM gridcluster_customers GROUP BY c_nationkey"
    return spark.sql(f"SELECT c_nationkey, anchor_id, round(feats[0], 6) + 0D AS f0, round(feats[1], 6) + 0D AS f1 FROM ({bounds}) b, LATERAL anchor_rows(50, b.lows, b.highs, CAST(b.c_nationkey AS INT))")


@query
def solo_vs_pooled_assignments(spark, sf_dir):
    """How labels from half of the features agree with labels from all, under fixed centers."""
    v = vectors(spark, sf_dir)
    own = kmeans.assign(v.select("row_id", F.slice("z", 1, DIMS // 2).alias("z")), CENTERS[:, : DIMS // 2], label="solo").select("row_id", "solo")
    return kmeans.assign(v, CENTERS).join(own, "row_id").groupBy("pred", "solo").agg(F.count(F.lit(1)).alias("n"))


def _orders_ledger(spark, sf_dir):
    o = load(spark, sf_dir, "orders", ["o_orderkey", "o_orderpriority", "o_orderstatus", "o_totalprice"])
    method = F.when(F.col("o_orderstatus") == "F", "pooled").when(F.col("o_orderstatus") == "O", "grid").otherwise("solo")
    return o.select(F.col("o_orderpriority").alias("dataset"), method.alias("method"), F.col("o_orderkey").alias("trial"), F.lit("ari").alias("metric"), (F.col("o_totalprice") / 1e5).alias("value"))


@query
def trial_summary(spark, sf_dir):
    return diagnostics.summarise_trials(_orders_ledger(spark, sf_dir)).select("dataset", "method", "metric", r("mean").alias("mean"), r("sd").alias("sd"), "trials")


@query
def pct_delta(spark, sf_dir):
    return diagnostics.pct_delta(diagnostics.summarise_trials(_orders_ledger(spark, sf_dir))).select("dataset", "method", "metric", r("pct", 4).alias("pct"), r("signed_pct", 4).alias("signed_pct"))


@query
def avg_pct_delta(spark, sf_dir):
    return workloads.deviation_report(_orders_ledger(spark, sf_dir)).select("method", r("avg_pct", 4).alias("avg_pct"))


@query
def method_ranks(spark, sf_dir):
    return diagnostics.rank_methods(diagnostics.summarise_trials(_orders_ledger(spark, sf_dir))).select("dataset", "method", "metric", "rank")


@query
def wide_report(spark, sf_dir):
    w = diagnostics.wide_table(diagnostics.summarise_trials(_orders_ledger(spark, sf_dir)))
    return w.select("dataset", "method", r("ari").alias("ari"))


@query
def dataset_cards(spark, sf_dir):
    return metrics.dataset_card(workloads.text_language(spark, sf_dir), 10)


# -- operators around ------------------------------------------------------------------------------------------


@query
def text_profile(spark, sf_dir):
    p = workloads.text_language(spark, sf_dir)
    return p.select("row_id", "truth", *(r(F.col("feats")[i]).alias(f"f{i}") for i in range(10)))


@query
def quality_profile(spark, sf_dir):
    p = workloads.text_quality(spark, sf_dir)
    return p.select("row_id", "truth", r(F.col("feats")[1]).alias("digits"), r(F.col("feats")[2]).alias("blanks"), r(F.col("feats")[4]).alias("upper"))


@query
def html_profile(spark, sf_dir):
    t = features.html_text(F.col("html"))
    return load(spark, sf_dir, "pages").select("page_id", *(r(x).alias(f"s{i}") for i, x in enumerate(features.letter_shares(t, "aeiou"))))


@query
def events_profile(spark, sf_dir):
    p = features.events_profile(load(spark, sf_dir, "events"))
    return p.select("row_id", r(F.col("feats")[0]).alias("value"), F.col("feats")[1].cast("int").alias("hour"), F.col("feats")[2].cast("int").alias("weekday"), F.col("feats")[3].cast("int").alias("k"))


@query
def order_behaviour(spark, sf_dir):
    p = workloads.customer_orders(spark, sf_dir)
    return p.select("row_id", "row_grp", *(r(F.col("feats")[i], 5).alias(f"f{i}") for i in range(6)))


@query
def order_dates(spark, sf_dir):
    return features.date_parts(load(spark, sf_dir, "orders", ["o_orderkey", "o_orderdate"]), "o_orderdate").drop("o_orderdate")


@query
def category_index(spark, sf_dir):
    return features.index_category(load(spark, sf_dir, "customer", ["c_custkey", "c_mktsegment"]), "c_mktsegment")


@query
def vector_algebra(spark, sf_dir):
    v = vectors(spark, sf_dir)
    one = F.array(*(F.lit(0.1 * i) for i in range(DIMS)))
    return v.select("row_id", r(dot(F.col("z"), one)).alias("dot"), r(sqdist(F.col("z"), one)).alias("sqdist"), r(norm(F.col("z"))).alias("norm"))


@query
def layout_round_trip(spark, sf_dir):
    """Arrays to long rows and back to wide columns."""
    p = parts(spark, sf_dir).select("row_id", "feats")
    return layout.to_wide(layout.from_long(layout.to_long(p)), 4)


def _profile_rows(spark, sf_dir):
    return load(spark, sf_dir, "documents", ["doc_id"]).select(F.col("doc_id").alias("row_id"))


def _labelled_rows(spark, sf_dir):
    """Rows that a second holder knows: labels cover some of the documents."""
    return load(spark, sf_dir, "labels", ["doc_id"]).select(F.col("doc_id").alias("row_id")).distinct()


@query
def lattice_missing_rows(spark, sf_dir):
    return grid.missing_rows(_profile_rows(spark, sf_dir), [_profile_rows(spark, sf_dir), _labelled_rows(spark, sf_dir)])


@query
def lattice_complete_rows(spark, sf_dir):
    return grid.complete_rows(_profile_rows(spark, sf_dir), [_profile_rows(spark, sf_dir), _labelled_rows(spark, sf_dir)])


@query
def row_id_except(spark, sf_dir):
    return grid.extra_ids(_profile_rows(spark, sf_dir), _labelled_rows(spark, sf_dir))


@query
def row_id_intersect(spark, sf_dir):
    return grid.shared_ids(_profile_rows(spark, sf_dir), _labelled_rows(spark, sf_dir))


@query
def stack_union(spark, sf_dir):
    both = grid.stack([_profile_rows(spark, sf_dir), _labelled_rows(spark, sf_dir)])
    return both.groupBy("row_id").agg(F.count(F.lit(1)).alias("n"))


@query
def label_counts(spark, sf_dir):
    return diagnostics.label_counts(assigned(spark, sf_dir))


@query
def outliers(spark, sf_dir):
    return diagnostics.outliers(assigned(spark, sf_dir), 20).select("row_id", r("dist").alias("dist"))


@query
def distance_quantiles(spark, sf_dir):
    q = diagnostics.distance_quantiles(assigned(spark, sf_dir), exact=True)
    return q.select("pred", *(r(F.col("quantiles")[i]).alias(n) for i, n in enumerate(("p50", "p90", "p99"))))


@query
def center_shift(spark, sf_dir):
    v = vectors(spark, sf_dir)
    start = {0: [kmeans.seed_fixed(v, 3)]}
    history = [(p, k, c.tolist()) for p in range(4) for k, c in enumerate(kmeans.lloyd(v, start, p)[0][0].centers)]
    return diagnostics.center_shift(spark.createDataFrame(history, "pass int, cluster int, center array<double>")).withColumn("shift", r("shift"))


@query
def hash_sample_rows(spark, sf_dir):
    return hash_sample(lines(spark, sf_dir), 0.1, seed=4).select("row_id", *(F.col("feats")[i].alias(f"f{i}") for i in range(5)))


@query
def encode_uncentered(spark, sf_dir):
    """Codes of maps about zero."""
    p = parts(spark, sf_dir)
    codes = partymap.encode(p, TWO_BY_TWO, partymap.fit_pca_maps(p, TWO_BY_TWO, scale=False, center=False))
    return codes.select("row_id", "row_grp", "col_grp", r(F.col("code")[0], 5).alias("code"))


@query
def encode_rotated_norms(spark, sf_dir):
    """A secret rotation changes codes, not their lengths."""
    p = parts(spark, sf_dir)
    codes = partymap.encode(p, TWO_BY_TWO, partymap.fit_pca_maps(p, TWO_BY_TWO, width=2, allow_full=True, scale=False, rotate_seed=7))
    return codes.select("row_id", "col_grp", r(norm(F.col("code")), 5).alias("length"))


@query
def knn_include_self(spark, sf_dir):
    return graph.knn_graph(vectors(spark, sf_dir), q=5, include_self=True).select("src", "dst", r("dist").alias("dist"))


@query
def spectral_row_normalised(spark, sf_dir):
    """Rows of the embedding at length one."""
    p = workloads.text_language(spark, sf_dir).select("row_id", F.col("feats").alias("z"))
    z, _ = spectral_ops.embed(spark, materialise(spark, graph.symmetrise(graph.knn_graph(p, 10)), "edges"), 4, row_normalise=True)
    return z.select("row_id", r(norm(F.col("z"))).alias("length"))


def _segments(spark, sf_dir):
    """Mean order price by status: customers without an order of a status have no mean."""
    o = load(spark, sf_dir, "orders", ["o_custkey", "o_orderstatus", "o_totalprice"])
    return o.groupBy(F.col("o_custkey").alias("row_id")).pivot("o_orderstatus", ["F", "O", "P"]).agg(F.avg("o_totalprice"))


@query
def null_policy_drop(spark, sf_dir):
    return features.clean(_segments(spark, sf_dir), ["F", "O", "P"]).select("row_id", *(r(c).alias(c.lower()) for c in "FOP"))


@query
def null_policy_zero(spark, sf_dir):
    return features.clean(_segments(spark, sf_dir), ["F", "O", "P"], "zero").select("row_id", *(r(c).alias(c.lower()) for c in "FOP"))


@query
def null_policy_mean(spark, sf_dir):
    return features.clean(_segments(spark, sf_dir), ["F", "O", "P"], "mean").select("row_id", *(r(c).alias(c.lower()) for c in "FOP"))


@query
def one_hot_segments(spark, sf_dir):
    names = ["AUTOMOBILE", "BUILDING", "FURNITURE"]
    hot = features.one_hot(load(spark, sf_dir, "customer", ["c_custkey", "c_mktsegment"]), "c_mktsegment", names)
    return hot.select("c_custkey", *(F.col("c_mktsegment_hot")[i].cast("int").alias(n.lower()) for i, n in enumerate(names)))


@query
def block_files(spark, sf_dir):
    """Blocks written a folder a party, and read back by one party's folder."""
    path = f"{shared_dir(spark)}/blocks-{uuid.uuid4().hex}"
    p = parts(spark, sf_dir)
    for j in range(2):
        write_blocks(grid.block(p, TWO_BY_TWO, None, j).withColumn("col_grp", F.lit(j)), f"{path}/{j}")
    return spark.read.parquet(f"{path}/0").where("row_grp = 1").select("row_id", r(F.col("feats")[0]).alias("f0"), r(F.col("feats")[1]).alias("f1"))


@query
def model_files(spark, sf_dir):
    """Centers saved as a model, loaded, and used."""
    path = f"{shared_dir(spark)}/model-{uuid.uuid4().hex}"
    save_model(spark, {"centers": CENTERS}, path)
    found = kmeans.assign(vectors(spark, sf_dir), np.array(load_model(spark, path)["centers"]))
    return found.groupBy("pred").agg(F.count(F.lit(1)).alias("n"))


def _text_files(spark, sf_dir, fmt, schema):
    path = f"{shared_dir(spark)}/{fmt}-{uuid.uuid4().hex}"
    load(spark, sf_dir, "region", ["r_regionkey", "r_name"]).write.format(fmt).save(path)
    return load_text(spark, path, fmt, schema)


@query
def csv_scan(spark, sf_dir):
    return _text_files(spark, sf_dir, "csv", "r_regionkey int, r_name string")


@query
def json_scan(spark, sf_dir):
    return _text_files(spark, sf_dir, "json", "r_regionkey int, r_name string")


@query
def long_report(spark, sf_dir):
    """The wide report back to a row a measure; measures without a value are null."""
    w = diagnostics.wide_table(diagnostics.summarise_trials(_orders_ledger(spark, sf_dir)))
    return diagnostics.long_table(w).select("dataset", "method", "metric", r("mean").alias("mean"))


@query
def encode_code_sql(spark, sf_dir):
    """A party's code through the registered SQL function."""
    sqlapi.register_all(spark)
    parts(spark, sf_dir).createOrReplaceTempView("gridcluster_parts")
    return spark.sql("SELECT row_id, round(c[0], 6) + 0.0 AS c0, round(c[1], 6) + 0.0 AS c1 FROM (SELECT row_id, encode_code(feats, array(25D, 9D, 6D, 5D), array(2D, 1D, 1D, 4D), array(array(1D, 0D), array(0D, 1D), array(0.5D, 0D), array(0D, 0.25D))) AS c FROM gridcluster_parts)")


# -- events ----------------------------------------------------------------------------------------------------


def _scored_events(spark, sf_dir):
    e = features.events_profile(load(spark, sf_dir, "events")).select(F.col("row_id").alias("event_id"), "ts", "user_id", F.slice("feats", 1, 2).alias("feats"))
    return scoring.score(e, np.array([[20.0, 6.0], [20.0, 18.0], [80.0, 12.0]]))


@query
def event_scores_tumbling(spark, sf_dir):
    return scoring.label_counts(_scored_events(spark, sf_dir), "tumbling", "1 hour")


@query
def event_scores_sliding(spark, sf_dir):
    return scoring.label_counts(_scored_events(spark, sf_dir), "sliding", "1 hour", "30 minutes")


@query
def event_scores_session(spark, sf_dir):
    return scoring.label_counts(_scored_events(spark, sf_dir), "session", gap="30 minutes")


@query
def event_latest_model(spark, sf_dir):
    """Events with the newest version in force at their time; every sign-up is a version."""
    e = load(spark, sf_dir, "events", ["event_id", "ts", "user_id", "event_type"])
    v = e.where("event_type = 'signup'").groupBy("ts").agg(F.max("event_id").alias("version"))
    return scoring.latest_model(e.select("event_id", "ts"), v).select("event_id", "version")


@query
def event_pairs_within(spark, sf_dir):
    e = load(spark, sf_dir, "events", ["event_id", "ts", "user_id"])
    pairs = scoring.within(e, e, 600)
    return pairs.where(F.col("event_id") < F.col("other.event_id")).select(F.col("event_id").alias("a"), F.col("other.event_id").alias("b"))


# -- whole methods ---------------------------------------------------------------------------------------------


def _language(spark, sf_dir, groups=2, columns=2):
    p = materialise(spark, split_grid(workloads.text_language(spark, sf_dir), groups), "language")
    return p, GridSpec(even_columns(10, columns))


def _with_truth(labels: DataFrame, points: DataFrame) -> DataFrame:
    return labels.join(points.select("row_id", "truth"), "row_id").select("row_id", "row_grp", "truth", "pred")


@query
def grid_kmeans_language(spark, sf_dir):
    p, spec = _language(spark, sf_dir)
    return _with_truth(grid_cluster(p, spec, 4, restarts=5, fuse=True).labels, p)


@query
def grid_kmeans_protocol(spark, sf_dir):
    """As above, every step on its side of the parties' borders; the messages."""
    p, spec = _language(spark, sf_dir)
    return grid_cluster(p, spec, 4, restarts=2, passes=20).ledger.frame(spark)


@query
def grid_spectral_language(spark, sf_dir):
    p, spec = _language(spark, sf_dir)
    return _with_truth(grid_cluster(p, spec, 4, "spectral", restarts=3, fuse=True).labels, p)


@query
def grid_landmarks_language(spark, sf_dir):
    p, spec = _language(spark, sf_dir)
    return _with_truth(grid_cluster(p, spec, 4, "spectral", landmarks=100, fuse=True).labels, p)


@query
def grid_lpp_language(spark, sf_dir):
    p, spec = _language(spark, sf_dir)
    return _with_truth(grid_cluster(p, spec, 4, map_kind="lpp", restarts=5, passes=50, fuse=True).labels, p)


@query
def grid_autoencoder_language(spark, sf_dir):
    p, spec = _language(spark, sf_dir)
    return _with_truth(grid_cluster(p, spec, 4, map_kind="autoencoder", restarts=5, passes=50).labels, p)


@query
def pooled_kmeans_language(spark, sf_dir):
    p, _ = _language(spark, sf_dir)
    return _with_truth(baselines.pooled(p, 4, restarts=5), p)


@query
def pooled_spectral_language(spark, sf_dir):
    p, _ = _language(spark, sf_dir)
    return _with_truth(baselines.pooled(p, 4, "spectral", restarts=3), p)


@query
def solo_kmeans_language(spark, sf_dir):
    p, spec = _language(spark, sf_dir)
    return _with_truth(baselines.solo(p, spec, 0, 0, 4, restarts=5), p)


@query
def fed_kmeans_language(spark, sf_dir):
    p, spec = _language(spark, sf_dir, groups=10)
    return _with_truth(baselines.fed_kmeans(p, spec, 4)[0], p)


@query
def fed_spectral_language(spark, sf_dir):
    p, spec = _language(spark, sf_dir, groups=10)
    return _with_truth(baselines.fed_spectral(p, spec, 4)[0], p)


@query
def aligner_ablation(spark, sf_dir):
    """Rows split by language: affine, linear and no aligner."""
    p = materialise(spark, grid.sorted_groups(workloads.text_language(spark, sf_dir), "truth", 4), "sorted")
    spec = GridSpec(even_columns(10, 2))
    rows = []
    for kind in ("affine", "linear", "none"):
        s = metrics.scores(_with_truth(grid_cluster(p, spec, 4, aligner=kind, restarts=5, passes=50, fuse=kind != "none").labels, p))
        rows.append((kind, s["ari"], s["nmi"], s["acc"]))
    return spark.createDataFrame(rows, "aligner string, ari double, nmi double, acc double")


@query
def customers_by_region(spark, sf_dir):
    """Agreement of grid labels with pooled ones on a table without classes."""
    p = materialise(spark, workloads.customer_orders(spark, sf_dir), "customers")
    spec = GridSpec(((0, 1), (2, 3, 4, 5)))
    s = metrics.agreement(grid_cluster(p, spec, 3, restarts=3, passes=50, fuse=True).labels, baselines.pooled(p, 3, scale="standard", restarts=3, passes=50))
    return spark.createDataFrame([(s["ari"], s["nmi"], s["acc"])], "ari double, nmi double, acc double")


@query
def lineitem_grid(spark, sf_dir):
    """The scale workload: all order lines, ten by two parties, six clusters, twenty passes."""
    p = split_grid(lines(spark, sf_dir), 10)
    return grid_cluster(p, GridSpec(((0, 1, 2), (3, 4))), 6, passes=20, fuse=True).labels


@query
def estimator_language(spark, sf_dir):
    p, spec = _language(spark, sf_dir)
    return GridClusterer(spec, 4).fit(p).transform(p.select("row_id", "row_grp", "feats", "truth")).select("row_id", "truth", "pred")


def _exp1(name, shape, split, **options):
    REGISTRY[name] = lambda spark, sf_dir: workloads.run_exp1(spark, sf_dir, shape, split, **options)


for _shape in ("blobs", "rings"):
    for _split in ("iid", "skew"):
        _exp1(f"exp1_{_shape}_{_split}", _shape, _split)
        # the recipe as printed: standardise, reduce, align to orthonormal targets
        _exp1(f"exp1_{_shape}_{_split}_recipe", _shape, _split, scale=True, target="U")


#: Trials of the registered queries.
TRIALS = {"kmeans": 100, "spectral": 100}


def _exp2(name, dataset, algo, **options):
    REGISTRY[name] = lambda spark, sf_dir: workloads.run_exp2(spark, sf_dir, dataset, algo, TRIALS[algo], **options)


for _name in workloads.DATASETS:
    for _algo in TRIALS:
        _exp2(f"exp2_{_algo}_{_name}", _name, _algo)


@query
def exp2_summary(spark, sf_dir):
    """Mean and deviation over 100 trials of k-means on the three-class table, with differences to pooled and ranks."""
    summary = diagnostics.summarise_trials(workloads.run_exp2(spark, sf_dir, "small_three", "kmeans", TRIALS["kmeans"]))
    ranks = diagnostics.rank_methods(summary).select("dataset", "method", "metric", "rank")
    return summary.join(diagnostics.pct_delta(summary), ["dataset", "method", "metric"], "left").join(ranks, ["dataset", "method", "metric"])


@query
def exp2_average_deviation(spark, sf_dir):
    """Average difference to pooled over the six tables and three measures, by method, for both algorithms."""
    return workloads.average_deviations(spark, sf_dir, TRIALS["kmeans"], TRIALS["spectral"])


@query
def exp2_federation_steps(spark, sf_dir):
    """Federated k-means with five and with ten steps."""
    runs = [diagnostics.summarise_trials(workloads.run_exp2(spark, sf_dir, d, "kmeans", TRIALS["kmeans"], methods=("fed",), rounds=n)).withColumn("steps", F.lit(n)) for d in ("small_three", "ten_classes") for n in (5, 10)]
    return grid.stack(runs)


@query
def exp2_aligner_kinds(spark, sf_dir):
    """Affine, linear and no aligner under the second experiment's cut."""
    runs = [diagnostics.summarise_trials(workloads.run_exp2(spark, sf_dir, d, "kmeans", TRIALS["kmeans"], methods=("grid",), aligner=kind)).withColumn("aligner", F.lit(kind)) for d in ("small_three", "language") for kind in ("affine", "linear", "none")]
    return grid.stack(runs)
