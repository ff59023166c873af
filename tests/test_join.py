import math
import random

import pytest
from pyspark.sql import functions as F

from allpairs import costs, measures, planner
from allpairs.baselines.brute_force import brute_force, ruzicka_disjunctive
from allpairs.baselines.late_join import late_join
from allpairs.baselines.minhash_lsh import minhash_lsh, recall_precision
from allpairs.baselines.prefix_replication import OverBudget, prefix_replication
from allpairs.graph.components import communities
from allpairs.join import attach, similarity_join, similarity_join_rs, top_k
from allpairs.joining import LookupTableTooLarge, attach_online
from allpairs.model import InvalidRaw, as_sets, expand_to_set, normalize_raw, validate_raw
from allpairs.partials import classify, decompose_disjunctive, disjunctive_sums, measure_of
from allpairs.preprocess import drop_small_entities, drop_stop_words


def pairs(df):
    return {(r["e1"], r["e2"]): round(r["sim"], 9) for r in df.collect()}


SF = "/root/testdata/sf0.001"
HAND = {"ruzicka": 0.25, "jaccard": 0.5, "dice_set": 4 / 6, "dice_multiset": 0.4, "cosine_set": 2 / 3, "cosine_multiset": 2 / math.sqrt(24), "cosine_vector": 4 / math.sqrt(84), "overlap": 2, "inner_product": 4, "union_size": 8}


@pytest.mark.parametrize("name", HAND)
def test_measures_by_hand(tiny, name):
    found = pairs(similarity_join(tiny, name, 1e-9))
    assert set(found) == {(1, 2), (2, 3), (1, 3)}
    assert found[1, 2] == found[2, 3] == round(HAND[name], 9)


def test_distance_and_ties(tiny):
    assert pairs(similarity_join(tiny, "symmetric_difference", 6)) == {(1, 2): 6, (2, 3): 6, (1, 3): 0}
    assert len(pairs(similarity_join(tiny, "jaccard", 0.5))) == 3
    assert set(pairs(similarity_join(tiny, "jaccard", 0.5, inclusive=False))) == {(1, 3)}


def test_stop_words_small_entities_and_expansion(tiny):
    assert pairs(similarity_join(tiny, "ruzicka", 0.1, q=2)) == {(1, 3): 1.0}
    assert drop_stop_words(tiny, 2, "bounded").exceptAll(drop_stop_words(tiny, 2)).count() == 0
    assert {r["entity"] for r in drop_small_entities(tiny, 2).collect()} == {1, 2, 3}
    assert pairs(similarity_join(expand_to_set(tiny), "jaccard", 0.1)) == pairs(similarity_join(tiny, "ruzicka", 0.1))


def test_refusals(tiny, spark):
    with pytest.raises(ValueError):
        similarity_join(tiny, "ruzicka", 0)
    with pytest.raises(LookupTableTooLarge):
        attach(tiny, measures.ruzicka(), joining="lookup", max_table_bytes=10)
    with pytest.raises(measures.UnsupportedMeasure):
        decompose_disjunctive("largest_gap", lambda a, b: F.abs(a - b), aggregate="max")
    with pytest.raises(InvalidRaw):
        validate_raw(spark.range(3))
    with pytest.raises(OverBudget):
        prefix_replication(tiny, measures.jaccard(), 0.1, most_cells=1)
    with pytest.raises(planner.NotApplicable):
        planner.check_applicability(planner.Statistics(500, 100, 5, 5, 100, 24750))


def test_nulls_zeros_repeats_and_empty(spark):
    rows = [(1, "a", 1), (1, "a", 1), (2, "a", 2), (None, "a", 1), (3, None, 1), (4, "a", None), (5, "a", 0)]
    raw = spark.createDataFrame(rows, "entity long, element string, mult long")
    assert pairs(similarity_join(raw, "ruzicka", 0.5)) == {(1, 2): 1.0}
    assert similarity_join(raw.limit(0), "ruzicka", 0.5).count() == 0
    assert normalize_raw(raw).count() == 2


@pytest.fixture(scope="module")
def skewed(spark):
    rng = random.Random(5)
    cells = {}
    for e in range(120):
        base = rng.randrange(12)
        for _ in range(rng.randint(5, 20)):
            cells[e, f"x{base}_{min(int(rng.paretovariate(1.1)), 15)}"] = rng.randint(1, 4)
        cells[e, "everywhere"] = 1
    for k in range(600):
        cells[0, f"g{k}"] = cells[1, f"g{k + 20}"] = 1
    return spark.createDataFrame([(e, x, m) for (e, x), m in cells.items()], "entity long, element string, mult long").cache()


def test_every_joining_and_similarity_phase_agrees(skewed):
    m = measures.ruzicka()
    plain = attach(skewed, m, impl="window").select("entity", "element", "mult", "uni_card")
    ways = [dict(impl=i) for i in ("tagged", "smj", "salted", "buffered")] + [dict(joining="lookup")] + [dict(joining="sharding", C=c) for c in (0, 1, 32, 10_000)] + [dict(joining="sharding", C=32, route_giants=False)]
    for way in ways:
        other = attach(skewed, m, **way).select("entity", "element", "mult", "uni_card")
        assert plain.exceptAll(other).count() == 0 and other.exceptAll(plain).count() == 0, way
    for t in (0.1, 0.3, 0.6):
        exact = pairs(similarity_join(skewed, m, t))
        assert exact == pairs(brute_force(skewed, m, t))
        for options in (dict(similarity="chunked", T=3), dict(similarity="chunked", max_list_rows=25), dict(similarity="chunked", T=3, chunk_pairs="ordered"), dict(similarity="list"), dict(prune=True), dict(carry="first"), dict(carry="rejoin"), dict(similarity="aqe")):
            assert pairs(similarity_join(skewed, m, t, **options)) == exact, (t, options)


@pytest.mark.parametrize("name", ["jaccard", "dice_set", "cosine_set"])
def test_prefix_replication_is_exact(skewed, name):
    m = measures.by_name(name)
    for t in (0.3, 0.7):
        exact = pairs(similarity_join(skewed, m, t))
        for options in (dict(), dict(order="hash"), dict(grouping=16), dict(kernel="indexed"), dict(dedup="distinct", filters=())):
            assert pairs(prefix_replication(skewed, m, t, **options)) == exact, (t, options)


@pytest.mark.parametrize("name,t", [("jaccard", 0.5), ("ruzicka", 0.3), ("dice_multiset", 0.6), ("cosine_set", 0.7), ("cosine_multiset", 0.9), ("overlap", 3)])
def test_entities_that_can_be_in_no_pair_are_left_out(spark, skewed, name, t, monkeypatch):
    """Whole entities stay or go (F9, F11, F13 to F23), nothing of the result is lost, and lone entities go before lists are made."""
    from allpairs.similarity import possible as kernels

    lone = spark.range(100).select((F.col("id") % 10 + 10**6).alias("entity"), F.concat(F.lit("lone"), "id").alias("element"), F.lit(1).cast("long").alias("mult"))
    odd = spark.createDataFrame([(None, "a", 1), (10**7, None, 1), (10**7, "lone7", 1), (10**7, "b7", 0)], "entity long, element string, mult long")
    raw = skewed.select("entity", F.col("element").cast("string").alias("element"), F.col("mult").cast("long").alias("mult")).unionByName(lone).unionByName(odd)
    m = measures.by_name(name)
    for parts in (None, 1, 300):
        kept = kernels.possible(raw, m, t, parts)
        assert pairs(similarity_join(kept, m, t)) == pairs(similarity_join(raw, m, t))
        ids = {r["entity"] for r in kept.select("entity").distinct().collect()}
        assert kept.exceptAll(raw).count() == 0 and raw.filter(F.col("entity").isin(*ids)).count() == kept.filter("entity is not null").count()
        assert (not any(10**6 <= e < 10**6 + 10 and e != 10**6 + 7 for e in ids if e)) == kernels.applies(m)


def test_indexed_prefix_lists_are_read_in_one_stream(skewed, monkeypatch):
    """No Python call of its own for each of many short lists (F10); multisets too; lists that begin in one batch and end in another."""
    found = prefix_replication(skewed, measures.ruzicka(), 0.4, kernel="indexed")
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert "FlatMapGroups" not in plan and "MapInArrow" in plan
    assert pairs(found) == pairs(similarity_join(skewed, "ruzicka", 0.4))
    import random

    import pyarrow as pa

    from allpairs.baselines import prefix_replication as kernels

    rng = random.Random(4)
    rows = sorted((key, n, e, rng.sample(range(30), n)) for key in range(40) for e in range(rng.randint(1, 12)) for n in [rng.randint(1, 20)])
    table = pa.table({"key": [r[0] for r in rows], "n": [r[1] for r in rows], "entity": [r[2] for r in rows], "items": [r[3] for r in rows]})
    wanted = sorted((min(a[2], b[2]), max(a[2], b[2]), len({*a[3]} & {*b[3]})) for k, a in enumerate(rows) for b in rows[k + 1 :] if a[0] == b[0] and len({*a[3]} & {*b[3]}) >= 0.3 * len({*a[3], *b[3]}))
    for short, cells in ((1 << 13, 1 << 21), (20, 50), (0, 7)):
        monkeypatch.setattr(kernels, "SHORT_CELLS", short)
        monkeypatch.setattr(kernels, "LISTED_CELLS", cells)
        got = [(min(a, b), max(a, b), int(s)) for x in kernels._listed(table, measures.jaccard(), 0.3) for a, b, s in zip(*(x.column(c).to_pylist() for c in ("a", "b", "shared")))]
        assert sorted(got) == wanted


def test_prefix_length_at_a_binary_trap():
    assert measures.jaccard().prefix_len(30, 0.1) == 28


def test_algebra(skewed):
    assert classify(lambda x, y: x) == {"uni"} and classify(min) == {"conj"} and classify(max) == {"disj"} and classify(lambda x, y: abs(x - y)) == {"disj"}
    few = skewed.filter("entity between 10 and 40")
    exact = pairs(similarity_join(few, "ruzicka", 0.2))
    assert pairs(ruzicka_disjunctive(few, 0.2)) == exact == pairs(late_join(few, measures.ruzicka(), 0.2))
    union = decompose_disjunctive("union", lambda a, b: F.greatest(a, b))
    candidates = similarity_join(few, union, 1)
    direct = disjunctive_sums(few, candidates, lambda a, b: F.greatest(a, b))
    assert {(r["e1"], r["e2"]): float(r["value"]) for r in direct.collect()} == pairs(candidates)


def test_order_of_measures_and_monotone(skewed):
    sims = similarity_join(skewed, t=0.05, measures=["jaccard", "dice_set", "cosine_set"])
    assert sims.filter("sim_jaccard > sim_dice_set + 1e-9 or sim_dice_set > sim_cosine_set + 1e-9 or sim_cosine_set > 1 + 1e-9").count() == 0
    counts = [similarity_join(skewed, "ruzicka", t).count() for t in (0.1, 0.3, 0.5, 0.9)]
    assert counts == sorted(counts, reverse=True)


def test_two_collections_top_k_communities_and_lsh(skewed, spark):
    exact = pairs(similarity_join(skewed, "jaccard", 0.5))
    both = pairs(similarity_join_rs(as_sets(skewed), as_sets(skewed), "jaccard", 0.5))
    assert {k: v for k, v in both.items() if k[0] < k[1]} == exact
    assert top_k(similarity_join(skewed, "jaccard", 0.3), 2).groupBy("entity").count().filter("count > 2").count() == 0
    spark.sparkContext.setCheckpointDir("/tmp/allpairs-test-checkpoints")
    found = {r["entity"]: r["community"] for r in communities(similarity_join(skewed, "jaccard", 0.5)).collect()}
    parent = {x: x for p in exact for x in p}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in exact:
        a, b = root(a), root(b)
        parent[max(a, b)] = min(a, b)
    assert found == {x: root(x) for x in parent}
    r = recall_precision(minhash_lsh(skewed, measures.jaccard(), 0.5, 24, 2), similarity_join(skewed, "jaccard", 0.5)).first()
    assert r["precision"] == 1 and r["recall"] >= 0.9


def test_costs(tiny):
    c = costs.index_cost(tiny).first()
    assert (c["increments"], c["longest_list"]) == (7, 3)
    assert costs.max_intersection(tiny).first()["candidates"] == 3
    s = planner.statistics(tiny)
    assert (s.rows, s.entities, s.elements, s.increments) == (10, 4, 5, 7)
    assert [r["entries"] for r in costs.lookup_footprint(tiny, [2, 3]).orderBy("limit").collect()] == [3, 0]


@pytest.mark.parametrize("impl,combiner", [("window", "native"), ("smj", "native"), ("smj", "none"), ("salted", "native"), ("salted", "none"), ("tagged", "native"), ("tagged", "none"), ("tagged", "partition"), ("buffered", "native"), ("cogrouped", "native")])
@pytest.mark.parametrize("kind,measure", [("double", lambda: measures.ruzicka()), ("decimal(10,2)", lambda: measures.ruzicka()), ("double", lambda: measures.cosine("vector", norm="l1")), ("long", lambda: decompose_disjunctive("span", lambda a, b: F.abs(a - b)))])
def test_totals_of_any_measure_in_every_joining(spark, impl, combiner, kind, measure):
    rows = [(1, "a", 0.5), (1, "b", 1.5), (2, "a", 0.7), (2, "c", 0.2), (3, "a", 2.0)]
    scale = 10 if kind == "long" else 1
    raw = spark.createDataFrame([(e, x, m * scale) for e, x, m in rows], "entity long, element string, mult double").withColumn("mult", F.col("mult").cast(kind))
    m = measure()
    got = {r["entity"]: [round(float(r[f"uni_{n}"]), 9) for n in m.uni] for r in attach_online(raw, m, impl=impl, combiner=combiner).collect()}
    assert got == {e: [round(scale * v, 9)] * len(m.uni) for e, v in ((1, 2.0), (2, 0.9), (3, 2.0))}


def test_similarity_phase_chosen_from_counts(skewed, spark):
    exact = pairs(similarity_join(skewed, "ruzicka", 0.3))
    assert pairs(similarity_join(skewed, "ruzicka", 0.3, similarity="auto", joining="auto")) == exact
    assert pairs(similarity_join(skewed, "ruzicka", 0.3, similarity="auto", max_list_rows=20)) == exact
    assert pairs(similarity_join(skewed, "ruzicka", 0.3, similarity="chunked", max_list_rows=20, prune=True)) == exact
    for m in ("ruzicka", "jaccard", "dice_multiset", "cosine_set"):
        for t in (0.3, 0.5, 1.0):
            assert pairs(similarity_join(skewed, m, t, prune="bands")) == pairs(similarity_join(skewed, m, t)), (m, t)
    stats = planner.statistics(skewed)
    assert planner.choose_similarity(stats, True, 20).similarity == "chunked" and planner.choose_similarity(stats, False).similarity == "index"
    with pytest.raises(planner.NotApplicable):
        similarity_join(skewed, "ruzicka", 0.3, most_increments=10)
    histograms = spark.range(40).select(F.col("id").alias("entity"), F.explode(F.array(*(F.lit(f"bin{k}") for k in range(8)))).alias("element"), F.lit(1).cast("long").alias("mult"))
    with pytest.raises(planner.NotApplicable):
        similarity_join(histograms, "ruzicka", 0.3, similarity="auto")
    with pytest.raises(ValueError):
        similarity_join(skewed, "ruzicka", 0.3, similarity="list", prune=True)


def test_measures_from_plain_functions():
    own = measure_of("m", {"n": lambda x, y: x, "o": min}, {"n": lambda f, g: f, "o": F.least}, lambda c, a, b: c["o"] / a["n"])
    assert own.uni == ("n",) and set(own.conj) == {"o"}
    with pytest.raises(measures.UnsupportedMeasure):
        measure_of("m", {"u": max}, {"u": F.greatest}, lambda c, a, b: c["u"])


def test_outcomes_counters_and_plans(skewed, spark):
    from allpairs.counters import counted, explain_phases

    slow = F.udf(lambda x: __import__("time").sleep(3) or x, "long")
    assert costs.run(lambda: skewed.limit(4), 60).state == "ok"
    assert costs.run(lambda: spark.range(0, 40, 1, 8).filter(slow("id") >= 0), 1).state == "timeout"
    assert costs.run(lambda: spark.range(3).select(F.raise_error(F.lit("no room")).alias("x")).filter("x is not null")).state == "failed"
    with counted(spark) as c:
        similarity_join(skewed, "ruzicka", 0.3).count()
    assert c.stages and c.task_seconds > 0 and c.shuffled_bytes > 0 and c.slowest()["most_rows"] >= 0
    plans = explain_phases(skewed, measures.ruzicka(), 0.3)
    assert set(plans) == {"joining", "similarity", "whole"} and "Window" in plans["joining"] and "SortMergeJoin" in plans["similarity"]


def test_raw_rows_are_made_once(spark, skewed):
    from allpairs import scratch

    grouped = skewed.groupBy("entity", "element").agg(F.sum("mult").alias("mult"))
    assert scratch.derived(grouped) and not scratch.derived(scratch.written(grouped, "t").filter("mult > 1").select("entity"))
    calls = spark.sparkContext.accumulator(0)
    seen = F.udf(lambda x: calls.add(1) or x, "long")
    watched = grouped.withColumn("mult", seen("mult"))
    rows = grouped.count()
    for way in (dict(joining="lookup"), dict(joining="sharding", C=32)):
        before = calls.value
        attach(watched, measures.ruzicka(), **way).count()
        assert calls.value - before <= rows, way


def test_experiments_run(spark):
    from allpairs.experiments.runners import ablations, kernel_share, measure_swap, proxy_study, realistic_size, sharding_steps, threshold_sweep

    sweep = threshold_sweep(spark, SF, steps=(0.3, 0.7), repeat=1)
    assert len(sweep) == 8 and all(len({r["pairs"] for r in sweep if r["t"] == t}) == 1 for t in (0.3, 0.7))
    assert [r["state"] for r in realistic_size(spark, SF, repeat=1, lookup_bytes=100, most_cells=10)][:3] == ["table_too_large", "over_budget", "over_budget"]
    steps = sharding_steps(spark, SF, limits=(32, 1024), repeat=1)
    assert steps[0]["giants"] > steps[1]["giants"] and all(r["step1_seconds"] > 0 for r in steps)
    assert all(0 < r["kernel_share"] < 1 for r in kernel_share(spark, SF, steps=(0.5,), repeat=1))
    study = proxy_study(spark, SF, steps=(0.1, 0.9), sample_of=1)
    assert study[0]["covered"] >= study[1]["covered"] and {r["entities"] for r in study} == {"all", "min_50"}
    assert len(measure_swap(spark, SF, measures=("ruzicka", "jaccard"), repeat=1)) == 2 and len(ablations(spark, SF, repeat=1)) == 7


def test_late_rows_are_counted(spark, tmp_path):
    import os

    from allpairs.streaming.events import drained, late_rows

    for k, days in enumerate(([10, 10, 10], [10], [1, 2, 3, 11])):
        spark.createDataFrame([(i, f"2024-01-{d:02d} 00:00:00") for i, d in enumerate(days)], "id long, at string").selectExpr(f"id + {10 * k} as id", "cast(at as timestamp) as ts").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        for f in os.listdir(f"{tmp_path}/in"):
            if not os.path.exists(f"{tmp_path}/seen_{f}"):
                open(f"{tmp_path}/seen_{f}", "w").close()
                os.utime(f"{tmp_path}/in/{f}", (1_700_000_000 + 100 * k,) * 2)
    stream = spark.readStream.schema("id long, ts timestamp").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in").withWatermark("ts", "1 day").dropDuplicates(["id", "ts"])
    query = stream.writeStream.format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    # a batch is held to the watermark of the batch before the last
    assert late_rows(query) == 3 and spark.read.parquet(f"{tmp_path}/out").count() == 5
    counts = spark.readStream.schema("id long, ts timestamp").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in").groupBy(F.dayofmonth("ts").alias("day")).count()
    assert sorted(map(tuple, drained(counts, "update", "t", every="1 second", keys=("day",)).collect())) == [(1, 1), (2, 1), (3, 1), (10, 4), (11, 1)]


def test_large_tables_of_totals_are_not_broadcast(tiny, monkeypatch):
    from allpairs.joining import lookup

    want = sorted(attach(tiny, measures.ruzicka(), joining="lookup").collect())
    monkeypatch.setattr(lookup, "BROADCAST_BYTES", 100, raising=False)
    dealt = attach(tiny, measures.ruzicka(), joining="lookup")
    plan = dealt._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" not in plan and "ShuffledHashJoin" in plan
    assert sorted(dealt.collect()) == want


def shipped(spark, df):
    from allpairs.counters import counted

    with counted(spark) as c:
        n = df().count()
    return n, c.shuffled_bytes


@pytest.mark.parametrize("measure,t", [("ruzicka", 0.1), ("ruzicka", 0.5), ("jaccard", 0.3), ("dice_multiset", 0.4), ("dice_set", 0.4), ("cosine_set", 0.5), ("cosine_multiset", 0.5), ("cosine_vector", 0.6)])
def test_whole_blocks_agree(skewed, monkeypatch, measure, t):
    from allpairs.similarity import blocks

    exact = pairs(similarity_join(skewed, measure, t))
    assert pairs(similarity_join(skewed, measure, t, similarity="blocks")) == exact
    monkeypatch.setattr(blocks, "BLOCK_ENTITIES", 25)
    monkeypatch.setattr(blocks, "SLICE", 1000)
    assert pairs(similarity_join(skewed, measure, t, similarity="blocks")) == exact
    assert pairs(similarity_join(skewed, measure, t, similarity="blocks", symmetric_output=True)) == exact | {(b, a): v for (a, b), v in exact.items()}


def test_dense_vectors_ship_no_pairs(spark, monkeypatch):
    """All pairs share all elements; signs, strings and values that aren't finite stay what they are."""
    from allpairs.similarity import blocks

    rng = random.Random(4)
    rows = [(f"v{e}", x, rng.uniform(-1, 1)) for e in range(300) for x in range(16) if rng.random() < 0.9]
    raw = spark.createDataFrame(rows, "entity string, element int, mult double").cache()
    m = measures.cosine("vector", signed=True)
    exact = pairs(similarity_join(raw, m, 0.5))
    assert exact and pairs(similarity_join(raw, m, 0.5, similarity="blocks")) == exact
    n, moved = shipped(spark, lambda: similarity_join(raw, m, 0.5, similarity="blocks"))
    assert n == len(exact) and moved < shipped(spark, lambda: similarity_join(raw, m, 0.5))[1] / 4
    monkeypatch.setattr(blocks, "BLOCK_ENTITIES", 2)
    odd = spark.createDataFrame([(1, 0, math.nan), (1, 1, 1.0), (2, 1, 1.0), (3, 0, math.inf), (3, 2, 2.0), (4, 2, 2.0), (5, 1, 1.0)], "entity long, element int, mult double")
    show = lambda df: {k: str(v) for k, v in pairs(df).items()}
    assert show(similarity_join(odd, m, 0.5, similarity="blocks")) == show(similarity_join(odd, m, 0.5)) and (2, 5) in show(similarity_join(odd, m, 0.5, similarity="blocks"))
    assert similarity_join(raw.limit(0), m, 0.5, similarity="blocks").count() == 0
    with pytest.raises(measures.UnsupportedMeasure):
        similarity_join(odd, "union_size", 0.5, similarity="blocks")


def test_brute_force_joins_no_cells(skewed, spark):
    plan = brute_force(skewed, measures.ruzicka(), 0.3)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "CartesianProduct" not in plan
    expanded = expand_to_set(skewed.filter("entity < 20"))
    assert pairs(brute_force(expanded, measures.jaccard(), 0.3)) == pairs(similarity_join(expanded, "jaccard", 0.3))


@pytest.mark.parametrize("measure", ["ruzicka", "jaccard", "dice_multiset", "dice_set", "cosine_set", "cosine_multiset"])
def test_blocks_of_near_totals_agree(skewed, monkeypatch, measure):
    from allpairs.similarity import blocks

    monkeypatch.setattr(blocks, "MEETINGS", 50)
    for rows in (1 << 20, 200):
        monkeypatch.setattr(blocks, "PRUNED_ROWS", rows)
        for t in (0.2, 0.6, 1.0):
            assert pairs(similarity_join(skewed, measure, t, similarity="blocks", prune=True)) == pairs(similarity_join(skewed, measure, t)), (rows, t)


def test_word_lists_ship_no_candidates(spark):
    """Every two of these share common words, few are alike."""
    rng = random.Random(9)
    raw = spark.createDataFrame([(e, f"w{x}", 1) for e in range(400) for x in [*range(20), *rng.sample(range(20, 4000), 60)]], "entity long, element string, mult long").unionByName(spark.createDataFrame([(400 + k, f"w{x}", 1) for k in (0, 1) for x in range(90)], "entity long, element string, mult long")).cache()
    n, moved = shipped(spark, lambda: similarity_join(raw, "jaccard", 0.5, similarity="blocks", prune=True))
    assert n == 1 and moved < shipped(spark, lambda: similarity_join(raw, "jaccard", 0.5))[1] / 2


def test_numbered_elements_stand_for_their_strings():
    import pyarrow as pa

    from allpairs.similarity.blocks import _block

    table = pa.table({"common": pa.chunked_array([pa.array([[-32768, 32767], [], [5]], pa.list_(pa.int16()))]), "elements": pa.chunked_array([pa.array([[70_000], [65_536, 800_000], []], pa.list_(pa.int32()))])})
    ids, mults, starts = _block(table)
    assert ids.to_pylist() == [0, 65_535, 70_000, 65_536, 800_000, 32_773] and starts.tolist() == [0, 3, 5, 6] and mults.tolist() == [1.0] * 6


def test_sets_of_many_strings_keep_them(skewed, monkeypatch):
    from allpairs.similarity import blocks

    assert blocks.numbered(skewed).select("number").distinct().count() == skewed.select("element").distinct().count()
    monkeypatch.setattr(blocks, "MOST_NUMBERED", 3)
    assert blocks.numbered(skewed) is None
    assert pairs(similarity_join(skewed, "jaccard", 0.4, similarity="blocks", prune=True)) == pairs(similarity_join(skewed, "jaccard", 0.4))


def test_brute_force_skips_cells_without_a_number(spark):
    raw = spark.createDataFrame([(1, "a", 1), (1, "b", None), (1, "c", 1), (2, "a", 1), (2, "c", 1), (2, None, 1)], "entity long, element string, mult long")
    assert pairs(brute_force(raw, measures.ruzicka(), 0.1)) == {(1, 2): round(2 / 3, 9)}


@pytest.mark.parametrize("measure", ["jaccard", "ruzicka", "dice_set", "cosine_set"])
def test_prefixes_in_blocks_agree(skewed, monkeypatch, measure):
    from allpairs.similarity import blocks

    monkeypatch.setattr(blocks, "MEETINGS", 20)
    for t in (0.2, 0.6, 0.9, 1.0):
        assert pairs(prefix_replication(skewed, measures.by_name(measure), t, kernel="blocks")) == pairs(similarity_join(skewed, measure, t)), t


def test_prefixes_in_blocks_ship_each_record_a_few_times(spark):
    """Long records: most share nothing that is rare, and copies of them aren't made for each element of a prefix."""
    rng = random.Random(5)
    lists = [rng.sample(range(10**6), 400) for _ in range(60)]
    lists += [[*x[:-3], -1, -2, -3] for x in lists[:20]]
    raw = spark.createDataFrame([(e, f"x{x}", 1) for e, xs in enumerate(lists) for x in xs], "entity long, element string, mult long").cache()
    n, moved = shipped(spark, lambda: prefix_replication(raw, measures.jaccard(), 0.9, kernel="blocks"))
    assert n == 20 and moved < shipped(spark, lambda: prefix_replication(raw, measures.jaccard(), 0.9))[1] / 4


def test_registered_prefix_baseline_of_shingles_ships_less_than_its_cells(spark):
    """Shingles are counted where texts are dealt to, so that their strings don't move for it."""
    from allpairs.catalog import queries
    from allpairs.counters import counted
    from allpairs.workloads import doc_shingles

    rows = doc_shingles(spark, SF).count()
    with counted(spark) as c:
        queries()["baseline_prefix_frequency_doc_shingles"](spark, SF).count()
    assert c.shuffled_bytes < 40 * rows, c.shuffled_bytes / rows
    dealt = sorted(map(tuple, doc_shingles(spark, SF, dealt=True).collect()))
    assert dealt == sorted(map(tuple, doc_shingles(spark, SF).collect()))


@pytest.mark.parametrize("chunk", [2, 1024])
def test_lists_are_those_of_near_entities(spark, skewed, chunk, monkeypatch):
    """Entities that share only frequent elements never meet (F5, F6, F8 to F17), in whatever way lists are paired, and nothing of the result is lost."""
    from allpairs.baselines.late_join import late_join
    from allpairs.baselines.minhash_lsh import minhash_lsh
    from allpairs.similarity import possible as kernels

    monkeypatch.setattr(kernels, "NEAR_ENTITIES", chunk)
    monkeypatch.setattr(kernels, "MEETINGS", 7 if chunk == 2 else 1 << 20)
    # two of each kind are alike; all hold the same frequent elements
    made = [(10**6 + e, f"own{e // 2}-{k}", 1) for e in range(30) for k in range(9)] + [(10**6 + e, f"all{k}", 1) for e in range(30) for k in range(4)]
    raw = skewed.select("entity", F.col("element").cast("string").alias("element"), F.col("mult").cast("long").alias("mult")).unionByName(spark.createDataFrame(made, "entity long, element string, mult long"))
    m = measures.ruzicka()
    near = kernels.groups(raw, m, 0.5, 3)
    exact = pairs(similarity_join(raw, m, 0.5))
    assert len(exact) > 15
    for options in ({}, {"carry": "first"}, {"carry": "rejoin"}, {"similarity": "aqe"}, {"prune": True}, {"prune": "bands"}, {"similarity": "list"}, {"similarity": "auto", "joining": "auto"}, {"similarity": "chunked", "T": 4}, {"similarity": "chunked", "max_list_rows": 2, "prune": True}, {"similarity": "chunked", "T": 3, "chunk_pairs": "ordered", "prune": True}):
        assert pairs(similarity_join(raw, m, 0.5, near=near, **options)) == exact, options
    assert pairs(late_join(raw, m, 0.5, near=near)) == exact
    assert pairs(minhash_lsh(raw, m, 0.5, 8, 2, near=near)) == pairs(minhash_lsh(raw, m, 0.5, 8, 2))
    of_made = {r["entity"]: r["near"] for r in near.filter("entity >= 1000000").collect()}
    assert of_made == {10**6 + e: 10**6 + e // 2 * 2 for e in range(30)}
    plan = similarity_join(raw, m, 0.5, near=near)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("shufflepartitionidpassthrough") == 2 and "hashpartitioning(near" not in plan  # whole lists of a group move once
