import math

from dnfblock.operators import metrics


def test_paired_t():
    p, level = metrics.paired_t([1.0, 2.0, 3.0, 4.0, 5.0], [1.1, 2.3, 2.9, 4.4, 5.3])
    # t = -2.2361 with 4 degrees of freedom
    assert abs(p - 0.0890) < 1e-3 and level == "WS"
    assert metrics.paired_t([1.0, 1.0], [1.0, 1.0]) == (1.0, "NS")
    assert metrics.paired_t([2.0, 2.0], [1.0, 1.0]) == (0.0, "HS")


def test_incomplete_beta():
    assert abs(metrics.incomplete_beta(2, 3, 0.4) - 0.5248) < 1e-4
    assert abs(metrics.incomplete_beta(0.5, 0.5, 0.5) - 0.5) < 1e-12
    assert metrics.incomplete_beta(1, 1, 0) == 0 and metrics.incomplete_beta(1, 1, 1) == 1


def test_mapping_quality():
    true = ((("a",), ("x",)), (("b",), ("y", "z")))
    assert metrics.mapping_quality(((("a",), ("x",)), (("b",), ("z",))), true) == (1.0, 2 / 3, 1.0)
    assert metrics.mapping_quality(((("a",), ("y",)),), true) == (0.0, 0.0, 0.0)
    assert metrics.mapping_quality((), true) == (0.0, 0.0, 0.0)


def test_mean_sd():
    assert metrics.mean_sd([1.0, 3.0]) == (2.0, math.sqrt(2)) and metrics.mean_sd([4.0]) == (4.0, 0.0)


def test_precision_recall_over_buckets(spark):
    n = 10_000
    ranked = spark.range(1, n + 1).selectExpr("id AS rank", "cast(id AS string) AS l_rid", "cast(id AS string) AS r_rid")
    truth = ranked.where("rank % 3 = 0").select("l_rid", "r_rid")
    rows = {r.k: r for r in metrics.precision_recall_at(ranked, truth).collect()}
    hits = 0
    for k in range(1, n + 1):
        hits += k % 3 == 0
        if k in (1, 3, 4095, 4096, 4097, n):
            assert abs(rows[k].precision - hits / k) < 1e-12 and abs(rows[k].recall - hits / (n // 3)) < 1e-12
