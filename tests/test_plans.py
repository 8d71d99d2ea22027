import random

import pytest

from digitsort.plans import bins
from digitsort.plans.bins import Rules


@pytest.mark.parametrize("n,workers", [(60_000, 4), (0, 4), (7, 4), (31, 4), (1_000_003, 16), (5, 1)])
@pytest.mark.parametrize("growth", ["linear", "equal"])
def test_chunks_cover_everything(n, workers, growth):
    plan = bins.chunk_plan(n, workers, growth=growth)
    assert len(plan) == 8 * workers
    assert plan[0][1] == 0 and sum(x[2] for x in plan) == n
    assert all(a[1] + a[2] == b[1] for a, b in zip(plan, plan[1:], strict=False))


def test_chunks_grow_fifteenfold():
    sizes = [x[2] for x in bins.chunk_plan(60_000, 4)]
    assert abs(sizes[0] - 234.375) < 1 and abs(sizes[-1] - 3515.625) < 1
    assert all(b - a >= -1 for a, b in zip(sizes, sizes[1:], strict=False))


def test_teams_scaled_and_literal():
    r = Rules(workers=16)
    assert bins.teams(0, 100, r) == (0, 16)
    assert bins.teams(80, 100, r) == (16, 0)  # eight tenths take all
    assert bins.teams(40, 100, r) == (8, 8)
    assert bins.teams(40, 100, Rules(workers=16, team_rule="literal")) == (1, 15)
    assert bins.teams(100, 100, Rules(workers=16, team_rule="literal")) == (2, 14)
    assert bins.teams(100, 100, Rules(workers=16, team_rule="one")) == (0, 16)


def test_edges_of_constants(spark):
    from pyspark.sql import functions as F

    r = Rules(workers=4)
    df = spark.createDataFrame([(200, 1200), (201, 1200), (199, 1200)], "n long, total long")
    assert [x[0] for x in df.select(bins.is_heavy(F.col("n"), F.col("total"), r)).collect()] == [False, True, False]  # above 2N/3T only
    df = spark.createDataFrame([(383, 384), (384, 400), (100, 1600), (100, 1601), (32, 513), (33, 529)], "n long, p long")
    assert [x[0] for x in df.select(bins.is_tiny(F.col("n"), F.col("p"), Rules())).collect()] == [True, False, True, False, True, False]
    assert bins.pick_split(128 << 10) == "plain" and bins.pick_split((128 << 10) + 1) == "staged"
    assert [bins.shell_limit(b, r) for b in (8, 12, 16)] == [100, 140, 180]
    assert [bins.pick_tiny(n, 8, r) for n in (32, 33, 99, 100)] == ["insertion", "shell", "shell", "introspective"]


def test_longest_first_is_balanced():
    rng = random.Random(5)
    sizes = [rng.randrange(1, 100) for _ in range(200)]
    w = bins.longest_first(sizes, 8)
    load = [sum(s for s, x in zip(sizes, w, strict=True) if x == k) for k in range(8)]
    assert max(load) - min(load) <= max(sizes)


def test_schedule_prefers_largest_first_and_teams():
    light = [10] * 30 + [300]
    r = Rules(workers=4)
    assert bins.schedule([], light, sum(light), r)["finish"] <= bins.schedule([], light, sum(light), r, fifo=True)["finish"]
    alone = bins.schedule([], [1000, 10, 10, 10], 1030, Rules(workers=4, team_rule="one"))
    team = bins.schedule([1000], [10, 10, 10], 1030, r)
    assert team["finish"] < alone["finish"]


def test_decisions_match_known_counts(spark):
    """Counts on the 60,000-row workloads that were simulated independently."""
    from pyspark.sql import functions as F

    from digitsort.sources import workloads as wl

    d = "/root/testdata/sf0.01"
    found = {(r["side"], r["action"]): r["n"] for r in bins.decisions(wl.zipf(spark, d, scatter=True), "key", Rules(workers=16), 60_000).groupBy("side", "action").agg(F.count("*").alias("n")).collect()}
    assert found[("team", "light")] == 258 and found[("worker", "queued")] == 81 and found[("worker", "tiny")] == 645 + 288 + 41 + 25
    found = {(r["side"], r["action"]): r["n"] for r in bins.decisions(wl.uniform(spark, d), "key", Rules(workers=16), 60_000).groupBy("side", "action").agg(F.count("*").alias("n")).collect()}
    assert found == {("team", "light"): 256, ("worker", "tiny"): 39_366}
