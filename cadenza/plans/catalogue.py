"""All registered queries of the series engine, by name."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from cadenza.functions import arrays as A
from cadenza.functions import transforms as T
from cadenza.operators import joins, range_search
from cadenza.plans import oracles, surface
from cadenza.plans import workloads as W
from cadenza.streaming import windows

Query = Callable[[SparkSession, str], DataFrame]


def queries() -> dict[str, Query]:
    mavg = lambda m: lambda n: T.moving_average(n, m)
    twenty, five = [1 / 20] * 20, [1 / 5] * 5
    E, P = "embedding_walk", "supplier_walk"
    out: dict[str, Query] = {f"series_{k}": W.relation(k) for k in ("supplier_walk", "supplier_level", "embedding_walk", "embedding_level", "event_walk", "segment_sales", "doc_wordlen", "random_walk")}
    plain = [
        W.normal_form, W.normal_form_restore, W.rejected_series, W.dft_features, W.dft_spectrum, W.idft_roundtrip, W.energy_parseval, W.energy_concentration, W.circular_convolution, W.linearity_gap, W.mavg_standard, W.mavg_gap, W.mavg_repeated,
        W.affine_spectrum, W.safety_verdicts, W.safety_counterexample, W.index_nodes_cover, W.example_smoothing, W.example_stretch, W.example_stepwise, W.example_repeated_smoothing, W.range_single, W.range_shape, W.range_stretch, W.range_mean_sd,
        W.range_subset, W.range_real_vectors, W.join_two_relations, W.join_asymmetric, W.join_rect_unsafe, W.join_translation_one_side, W.lemma_joins_no_dismissals, W.knn_minmaxdist, W.join_regions, W.knn_join, W.dissimilarity_pairs, W.dissimilarity_range, W.dissimilarity_paths, W.dissimilarity_translations, W.lemma_no_dismissals, W.false_hits, W.measure_nodes, W.measure_nodes_equal, W.measure_coefficients, W.measure_answer_sweep, W.measure_index_quality, W.timed_methods,
    ]
    out |= {f.__name__: f for f in plain}
    out |= {
        "distance_euclidean": W.distance_to_first(E, A.euclid),
        "distance_cityblock": W.distance_to_first(E, A.cityblock),
        "mavg_circular": W.filtered(P, twenty),
        "mavg_trend": W.filtered("event_walk", T.trend_weights(5)),
        "mavg_center": W.filtered("event_walk", T.center_weights(5)),
        "kernel_difference": W.filtered("event_walk", [1.0, -1.0]),
        "identity_series": W._apply(E, T.identity),
        "reverse_series": W._apply(E, T.reverse),
        "shift_series": W._apply(E, lambda n: T.shift(n, 2.5)),
        "scale_series": W._apply(E, lambda n: T.scale(n, -1.5)),
        "stretch_series": W._apply(E, lambda n: T.stretch(n, 3)),
        "compose_transforms": W._apply(E, lambda n: T.scale(n, 2.0) @ T.reverse(n) @ T.shift(n, 1.0) @ T.moving_average(n, 4)),
        "range_plain": W.range_query(E, 3, 6.0),
        "range_identity": W.range_query(E, 3, 6.0, T.identity),
        "range_mavg": W.range_query(E, 3, 6.0, mavg(8)),
        "range_mavg_twosided": W.range_query(P, 3, 8.0, mavg(20), True),
        "range_auto": W.range_query(P, 3, 8.0, mavg(20), True, strategy="auto"),
        "range_rect_unsafe": W.range_query(P, 3, 8.0, mavg(20), True, space="rect"),
        "range_reverse": W.range_query(E, 3, 6.0, T.reverse),
        "range_trend": W.range_query(E, 3, 6.0, lambda n: T.trend(n, 8)),
        "range_rect_scale": W.range_query("supplier_level", 3, 874.0, lambda n: T.scale(n, 0.9), space="rect", normal=False, k=3),
        "range_rect_shift": W.range_query("supplier_level", 3, 930.0, lambda n: T.shift(n, 3.0), space="rect", normal=False, k=3),
        "range_rect_reverse": W.range_query("supplier_level", 3, 2625.0, T.reverse, space="rect", normal=False, k=3),
        "range_translation_folded": W.range_query(E, 3, 6.0, lambda n: T.shift(n, 0.1) @ T.moving_average(n, 8)),
        "scan_naive": W.scan(P, 3, 8.0, range_search.scan_naive, 20),
        "scan_abandon": W.scan(P, 3, 8.0, range_search.scan_abandon, 20),
        "scan_time": W.scan_time(P, 3, 8.0, 20),
        "scan_time_abandon": W.scan_time(P, 3, 8.0, 20, staged=32),
        "scan_plain_distance": W.scan_time(E, 3, 2.0, None, normal=False),
        "scan_normal_form": W.scan_time(E, 3, 6.0, None),
        "join_a_full": W.class_join(P, 20, 5.0, lambda ix, t, e: joins.scan_join(ix, t, e, False)),
        "join_b_abandon": W.join_method(P, 20, 5.0, lambda ix, t, e: joins.scan_join(ix, t, e, True)),
        "join_c_index": W.join_method(P, None, 5.0, joins.index_nested_loop),
        "join_d_index_mavg": W.class_join(P, 20, 5.0, joins.index_nested_loop),
        "join_tree": W.join_method(P, 20, 5.0, joins.self_join),
        "join_grid": W.join_method(P, 20, 5.0, lambda ix, t, e: joins.grid_join(ix, ix, t, t, e, True)),
        "join_documents": W.join_documents,
        "join_all_pairs": W.join_method(E, 8, 1.2, joins.self_join),
        "join_reverse": W.join_method(P, 20, 3.3, lambda ix, t, e: joins.self_join(ix, t, e, t_right=t @ T.reverse(ix.n))),
        "knn_plain": W.knn(None, "features"),
        "knn_mavg": W.knn(8, "features"),
        "knn_mindist": W.knn(8, "mindist"),
    }
    for n, count in oracles.WALKS:
        out |= {f"walk_identity_{n}_{count}": W.walk_queries(n, count, True), f"walk_plain_{n}_{count}": W.walk_queries(n, count, False), f"walk_scan_{n}_{count}": W.walk_scan(n, count)}
    return out | surface.queries() | windows.queries()


def oracle_sql() -> dict[str, str]:
    return oracles.catalogue() | surface.oracle_sql() | windows.oracle_sql()
