"""The queries of the search engine and their SQL."""

from __future__ import annotations

import functools
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracle as sql
from .functions.zorder import signatures, z_parent
from .model import Box, GridSpec
from .operators import baselines as base
from .operators import frontier
from .operators import search_datasets as sd
from .operators import search_points as sp
from .operators.bottom_index import build_bottom
from .operators.measures import dataset_boxes, hausdorff_scan, inverted_gbo, ranked, scan_gbo, scan_ia, summarise_nodes
from .operators.outliers import gap_profile, knee_threshold, mark_outliers
from .operators.relational import RELATIONAL
from .plans.metrics import overlap_accuracy, scale_distribution
from .plans.workloads import WORKLOADS, built, forget, w_chain
from .registry_index import QUERIES
from .sources.repositories import combine_queries, load_table, repository, repository_extent


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return w_chain(spark, sf_dir)


def first_id(points: DataFrame) -> str:
    return points.agg(F.min("dataset_id")).first()[0]


def last_id(points: DataFrame) -> str:
    return points.agg(F.max("dataset_id")).first()[0]


def rounded(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in columns})


def run_frame(spark: SparkSession, run: sd.Run, score: str, kind: type) -> DataFrame:
    rows = [(i, round(v, 6) if kind is float else int(v), r + 1) for r, (v, i) in enumerate(run.rows)]
    return spark.createDataFrame(rows, f"dataset_id string, {score} {'double' if kind is float else 'long'}, rank int")


def boxes_q(handle):
    return lambda s, d: rounded(dataset_boxes(repository(s, d, handle)), "lo0", "lo1", "hi0", "hi1")


def cells_q(handle, theta=5):
    def run(s, d):
        p = repository(s, d, handle)
        return signatures(p, GridSpec.from_extent(repository_extent(p), theta))

    return run


def rollup_q(s, d):
    return cells_q("ev_user")(s, d).groupBy(z_parent(F.col("cell"), 2).alias("cell")).agg(F.count(F.lit(1)).alias("n"))


def ia_q(handle):
    def run(s, d):
        i = built(s, d, handle)
        return run_frame(s, sd.topk_ia(i, first_id(i.roots)), "score", float)

    return run


def ia_scan_q(s, d):
    b = dataset_boxes(repository(s, d, "ev_home"))
    return rounded(scan_ia(b, first_id(b)), "score")


def gbo_q(handle, theta=5, plan="tree"):
    def run(s, d):
        i = built(s, d, handle, theta=theta)
        return run_frame(s, sd.topk_gbo(i, first_id(i.roots), plan=plan), "score", int)

    return run


def gbo_scan_q(s, d):
    p = repository(s, d, "ev_home")
    return scan_gbo(p, GridSpec.from_extent(repository_extent(p)), first_id(p))


def gbo_postings_q(s, d):
    return inverted_gbo(cells_q("ev_home")(s, d), first_id(repository(s, d, "ev_home")))


def haus_q(handle, method=sd.topk_hausdorff, k=10):
    def run(s, d):
        i = built(s, d, handle)
        return run_frame(s, method(i, first_id(i.roots), k), "distance", float)

    return run


def haus_scan_q(s, d):
    p = repository(s, d, "ev_home")
    return rounded(ranked(hausdorff_scan(p, first_id(p)), 10, "distance", False), "distance")


def haus_frontier_q(s, d):
    i = built(s, d, "pa_brand")
    q = first_id(i.roots)
    got = frontier.hausdorff(i.tree.filter(F.col("dataset_id") == q), i.tree.filter(F.col("dataset_id") != q))
    return rounded(ranked(got, 10, "distance", False), "distance")


def pair_q(s, d):
    i = built(s, d, "li_supp")
    return s.createDataFrame([(x, round(v, 6)) for v, x in sd.hausdorff_pair(i, first_id(i.roots), last_id(i.roots)).rows], "dataset_id string, distance double")


def approx_q(s, d):
    """For the true top-k: whether the approximate distance is within twice the error bound."""
    i = built(s, d, "ev_home")
    q = first_id(i.roots)
    truth = dict((x, v) for v, x in sd.topk_hausdorff(i, q).rows)
    n = i.roots.count()
    near = dict((x, v) for v, x in sd.topk_hausdorff(i, q, n, mode="approx").rows)
    eps = i.spec.epsilon()
    return s.createDataFrame([(x, x in near and abs(near[x] - v) <= 2 * eps) for x, v in truth.items()], "dataset_id string, within boolean")


def range_q(handle, grow):
    def run(s, d):
        i = built(s, d, handle)
        r = i.roots.filter(F.col("dataset_id") == first_id(i.roots)).first()
        e = [b - a for a, b in zip(i.spec.lo, i.spec.hi)]
        return sd.range_datasets(i, Box(tuple(r[f"lo{j}"] - grow * e[j] for j in (0, 1)), tuple(r[f"hi{j}"] + grow * e[j] for j in (0, 1))))

    return run


def range_batch_q(s, d):
    i = built(s, d, "ev_home")
    q = i.roots.select(F.col("dataset_id").alias("query_id"), *(F.col(f"{n}{j}").alias(f"q{n}{j}") for n in ("lo", "hi") for j in (0, 1)))
    return sd.range_datasets_batch(i, q)


def range_points_q(handle, scan=False):
    def run(s, d):
        i = built(s, d, handle)
        q = first_id(i.roots)
        r = i.roots.filter(F.col("dataset_id") == q).first()
        side = [r[f"hi{j}"] - r[f"lo{j}"] for j in (0, 1)]
        box = Box(tuple(r[f"lo{j}"] + side[j] * 0.25 for j in (0, 1)), tuple(r[f"hi{j}"] - side[j] * 0.25 for j in (0, 1)))
        got = base.scan_range_points(repository(s, d, handle), box, q) if scan else sp.range_points(i, box, q)
        return rounded(got, "c0", "c1")

    return run


def nearest_q(handle, k=1, strategy="packed"):
    def run(s, d):
        i = built(s, d, handle)
        return rounded(sp.nearest_points(i, first_id(i.roots), last_id(i.roots), k, strategy), "distance")

    return run


def knn_scan_q(s, d):
    p = repository(s, d, "ev_user")
    return rounded(base.knn_early_break(p, first_id(p), last_id(p)), "distance").select("q_point_id", "distance")


def nearest_union_q(s, d):
    i = built(s, d, "ev_user")
    ids = [r[0] for r in i.roots.select("dataset_id").filter(F.col("dataset_id") != last_id(i.roots)).collect()]
    return rounded(sp.nearest_points(i, combine_queries(i.points, ids, "query"), last_id(i.roots)).select("q_point_id", "distance"), "distance")


def accuracy_q(s, d):
    i = built(s, d, "ev_home")
    q = first_id(i.roots)
    return s.createDataFrame([(overlap_accuracy(sd.topk_gbo(i, q).rows, sd.topk_hausdorff(i, q).rows, 10),)], "accuracy double")


def pairs_q(s, d):
    return rounded(sd.similar_pairs(built(s, d, "pa_brand"), 40.0), "distance")


def isolation_q(s, d):
    return base.isolation_nn_scores(repository(s, d, "ev_user"), t=20)


def from_tables(query: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    """The query over indexes of its own: one that an earlier query has left would answer without reading the tables,
    and from what they held then."""

    @functools.wraps(query)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        forget()
        return query(spark, sf_dir)

    return run


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    out = {f"dataset_boxes_{h}": boxes_q(h) for h in ("ev_user", "li_supp", "or_cust")}
    out |= {f"z_signatures_{h}": cells_q(h) for h in ("ev_user", "li_supp")} | {"z_rollup": rollup_q}
    out |= {f"ia_topk_{h}": ia_q(h) for h in ("ev_home", "ev_trip", "li_part")} | {"ia_scan_topk": ia_scan_q}
    out |= {f"gbo_topk_{h}": gbo_q(h) for h in ("ev_home", "ev_user", "li_supp")}
    out |= {f"gbo_topk_theta{t}": gbo_q("ev_home", t) for t in (3, 7)} | {"gbo_topk_inverted": gbo_q("ev_home", plan="inverted"), "gbo_scan_topk": gbo_scan_q, "gbo_postings_topk": gbo_postings_q}
    out |= {f"hausdorff_topk_{h}": haus_q(h) for h in ("ev_home", "ev_slice", "ev_user", "li_supp", "pa_brand", "em_label", "li_wide")}
    out |= {"hausdorff_scan_topk": haus_scan_q, "hausdorff_box_bound_topk": haus_q("ev_home", base.box_bound_topk), "hausdorff_incremental_topk": haus_q("ev_home", base.box_incremental_topk), "hausdorff_raw_topk": haus_q("ev_home", base.raw_hausdorff_topk), "hausdorff_symmetric_topk": haus_q("ev_home", sd.symmetric_topk, 5), "hausdorff_frontier_topk": haus_frontier_q, "hausdorff_pair": pair_q, "approx_hausdorff_within_bound": approx_q}
    out |= {"range_datasets_ev_home": range_q("ev_home", 0.02), "range_datasets_ev_trip": range_q("ev_trip", 0.01), "range_datasets_batch": range_batch_q}
    out |= {"range_points_ev_user": range_points_q("ev_user"), "range_points_li_supp": range_points_q("li_supp"), "range_points_scan": range_points_q("ev_user", True)}
    out |= {"nearest_points_ev_user": nearest_q("ev_user"), "nearest_points_li_part": nearest_q("li_part"), "nearest_points_k3": nearest_q("ev_user", 3), "nearest_points_leaf_join": nearest_q("ev_user", 3, "leaf_join"), "nearest_points_per_point": nearest_q("ev_user", 3, "per_point"), "nearest_points_from_hausdorff": nearest_q("ev_user", 1, "from_hausdorff"), "nearest_points_early_break": nearest_q("ev_user", 1, "early_break"), "knn_scan_distance": knn_scan_q, "nearest_points_union": nearest_union_q}
    out |= {"topk_accuracy_gbo": accuracy_q, "similar_pairs": pairs_q, "isolation_scores": isolation_q}
    out |= {"scale_distribution": lambda s, d: scale_distribution(repository(s, d, "or_cust"))}
    out |= {k: f for k, (f, _) in RELATIONAL.items()} | dict(WORKLOADS) | {k: f for k, (f, _) in QUERIES.items()}
    return {name: from_tables(f) for name, f in out.items()}


def oracle_sql() -> dict[str, str]:
    out = {f"dataset_boxes_{h}": sql.dataset_boxes(h) for h in ("ev_user", "li_supp", "or_cust")}
    out |= {f"z_signatures_{h}": sql.z_signatures(h) for h in ("ev_user", "li_supp")} | {"z_rollup": sql.z_rollup("ev_user")}
    out |= {f"ia_topk_{h}": sql.ia_topk(h) for h in ("ev_home", "ev_trip", "li_part")} | {"ia_scan_topk": sql.ia_topk("ev_home")}
    out |= {f"gbo_topk_{h}": sql.gbo_topk(h) for h in ("ev_home", "ev_user", "li_supp")}
    out |= {f"gbo_topk_theta{t}": sql.gbo_topk("ev_home", t) for t in (3, 7)} | {k: sql.gbo_topk("ev_home") for k in ("gbo_topk_inverted", "gbo_scan_topk", "gbo_postings_topk")}
    out |= {f"hausdorff_topk_{h}": sql.haus_topk(h) for h in ("ev_home", "ev_slice", "ev_user", "li_supp", "pa_brand", "em_label", "li_wide")}
    out |= {k: sql.haus_topk("ev_home") for k in ("hausdorff_scan_topk", "hausdorff_box_bound_topk", "hausdorff_incremental_topk", "hausdorff_raw_topk")}
    out |= {"hausdorff_symmetric_topk": sql.symmetric("ev_home", 5), "hausdorff_frontier_topk": sql.haus_topk("pa_brand"), "hausdorff_pair": sql.haus_pair("li_supp"), "approx_hausdorff_within_bound": sql.haus_within("ev_home", 10)}
    out |= {"range_datasets_ev_home": sql.range_datasets("ev_home", 0.02), "range_datasets_ev_trip": sql.range_datasets("ev_trip", 0.01), "range_datasets_batch": sql.range_batch("ev_home")}
    out |= {"range_points_ev_user": sql.range_points("ev_user"), "range_points_li_supp": sql.range_points("li_supp"), "range_points_scan": sql.range_points("ev_user")}
    out |= {"nearest_points_ev_user": sql.nearest("ev_user"), "nearest_points_li_part": sql.nearest("li_part"), "nearest_points_k3": sql.nearest("ev_user", 3), "nearest_points_leaf_join": sql.nearest("ev_user", 3), "nearest_points_per_point": sql.nearest("ev_user", 3), "nearest_points_from_hausdorff": sql.nearest("ev_user"), "nearest_points_early_break": sql.nearest("ev_user"), "nearest_points_union": sql.nearest_union("ev_user")}
    out |= {"knn_scan_distance": f"SELECT q_point_id, distance FROM ({sql.nearest('ev_user')}) n"}
    out |= {"topk_accuracy_gbo": sql.gbo_accuracy("ev_home"), "similar_pairs": sql.similar_pairs("pa_brand", 40.0), "scale_distribution": sql.scale("or_cust")}
    out |= {k: text for k, (_, text) in (RELATIONAL | QUERIES).items() if text}
    return out
