"""Every registered query of the library, with the DuckDB statement for the same rows where there is one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import costs, oracles, planner, quality
from . import measures as M
from .baselines.brute_force import brute_force, ruzicka_disjunctive
from .baselines.late_join import late_join
from .baselines.minhash_lsh import minhash_lsh, recall_precision
from .baselines.prefix_replication import prefix_replication, rejoin_records, records, replication_cost
from .graph.components import communities
from .join import attach, similarity_join, similarity_join_rs, top_k
from .model import as_sets, expand_to_set, to_wide
from .partials import decompose_disjunctive, disjunctive_sums, measure_of, unilateral_totals
from .preprocess import element_frequency, frequency_histogram, idf_weighted, shuffle_alphabet, size_histogram
from .similarity.index import pair_increments
from .similarity.possible import applies, groups
from .sources.tables import read_table
from .workloads import RAW_SQL, WORKLOADS

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_SQL: dict[str, str] = {}
STEPS = [0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9]


def add(name: str, make: Query, sql: str | None = None) -> None:
    if name in _QUERIES:
        raise ValueError(f"{name} is registered twice")
    _QUERIES[name] = make
    if sql is not None:
        _SQL[name] = sql


def _rounded(pairs: DataFrame) -> DataFrame:
    return pairs.select("e1", "e2", F.round("sim", 9).alias("sim"))


def _near_shingles(s: SparkSession, d: str, measure: str | M.Measure, t: float) -> tuple[DataFrame, DataFrame | None]:
    """Shingles, and the groups that pairs are in; lists of all documents would be most of what is shuffled."""
    raw, m = WORKLOADS["doc_shingles"](s, d, dealt=True), M.by_name(measure) if isinstance(measure, str) else measure
    return raw, groups(WORKLOADS["doc_shingles"](s, d, dealt=True), m, t) if applies(m) else None


def _pairs(workload: str, measure: str | M.Measure, t: float, **options) -> Query:
    if workload == "doc_shingles" and 0.5 <= t <= 1:

        def near_pairs(s, d):
            raw, near = _near_shingles(s, d, measure, t)
            return _rounded(similarity_join(raw, measure, t, unique=True, near=near, **options))

        return near_pairs
    return lambda s, d: _rounded(similarity_join(WORKLOADS[workload](s, d), measure, t, unique=True, **options))


def _totals_and_profiles() -> None:
    for w in ("doc_words", "doc_shingles", "order_parts", "cust_parts", "supp_parts", "user_props"):
        add(f"uni_totals_{w}", lambda s, d, w=w: unilateral_totals(WORKLOADS[w](s, d), M.ruzicka(), M.jaccard()), oracles.totals(w, "card", "ucard"))
        add(f"element_frequency_{w}", lambda s, d, w=w: element_frequency(WORKLOADS[w](s, d)), f"SELECT element, count(*)::BIGINT AS freq FROM ({RAW_SQL[w]}) GROUP BY element")
    for w in ("doc_words", "doc_shingles", "order_parts", "page_words"):
        for name, of, make in (("size", "entity", size_histogram), ("frequency", "element", frequency_histogram)):
            add(f"{name}_histogram_{w}", lambda s, d, w=w, make=make: make(WORKLOADS[w](s, d)), f"SELECT (length(bin(n)) - 1)::BIGINT AS bin, count(*)::BIGINT AS count FROM (SELECT count(*)::BIGINT AS n FROM ({RAW_SQL[w]}) GROUP BY {of}) GROUP BY 1")
    for w in ("embeddings", "conv_words", "user_types", "benchmark_shingles"):
        add(f"raw_{w}", lambda s, d, w=w: WORKLOADS[w](s, d).withColumn("mult", F.round("mult", 6) if w == "embeddings" else F.col("mult")), f"SELECT entity, element, {'round(mult, 6)' if w == 'embeddings' else 'mult'} AS mult FROM ({RAW_SQL[w]})")
    add("wide_cells_user_types", lambda s, d: to_wide(WORKLOADS["user_types"](s, d)).select("entity", F.array_join(F.transform(F.map_entries("cells"), lambda x: F.concat_ws("=", x["key"], x["value"].cast("string"))), ",").alias("cells")), f"SELECT entity, string_agg(element || '=' || mult, ',' ORDER BY element) AS cells FROM ({RAW_SQL['user_types']}) GROUP BY entity")
    add("expanded_sets_order_parts", lambda s, d: expand_to_set(WORKLOADS["order_parts"](s, d)).select("entity", F.col("element.of").alias("element"), F.col("element.copy").alias("copy")), f"SELECT entity, element, unnest(range(1, mult + 1)) AS copy FROM ({RAW_SQL['order_parts']})")
    add("underlying_sets_user_props", lambda s, d: as_sets(WORKLOADS["user_props"](s, d)), f"SELECT entity, element, 1::BIGINT AS mult FROM ({RAW_SQL['user_props']})")


def _joining() -> None:
    w, sql = "supp_parts", oracles.joined("supp_parts", "card")

    def rows(**options) -> Query:
        return lambda s, d: attach(WORKLOADS[w](s, d), M.ruzicka(), **options).select("entity", "element", "mult", "uni_card")

    for impl in ("window", "tagged", "smj", "salted", "buffered", "cogrouped"):
        add(f"joined_online_{impl}", rows(impl=impl), sql)
    add("joined_lookup", rows(joining="lookup"), sql)
    for c in (0, 32, 510, 1_000_000):
        add(f"joined_sharding_c{c}", rows(joining="sharding", C=c), sql)
    add("joined_sharding_union", rows(joining="sharding", C=510, route_giants=False), sql)
    add("joined_overflow_to_sharding", rows(joining="lookup", max_table_bytes=4000, on_overflow="sharding", C=530), sql)
    add("joined_auto", rows(joining="auto"), sql)
    from .joining.online import attach_online

    # fractions, and a total of the measure's own
    vectors = "SELECT entity, element, round(mult, 6) AS mult, round(sum(mult * mult) OVER (PARTITION BY entity), 6) AS uni_sumsq, round(sum(abs(mult)) OVER (PARTITION BY entity), 6) AS uni_l1 FROM (%s)" % RAW_SQL["embeddings"]
    for name, options in (("window", {}), ("smj", {"impl": "smj"}), ("smj_none", {"impl": "smj", "combiner": "none"}), ("tagged", {"impl": "tagged"}), ("tagged_none", {"impl": "tagged", "combiner": "none"}), ("tagged_partition", {"impl": "tagged", "combiner": "partition"}), ("salted", {"impl": "salted"}), ("buffered", {"impl": "buffered"}), ("cogrouped", {"impl": "cogrouped"})):
        add(f"joined_vectors_{name}", lambda s, d, o=options: attach_online(WORKLOADS["embeddings"](s, d), M.cosine("vector"), M.cosine("vector", norm="l1"), **o).select("entity", "element", *(F.round(c, 6).alias(c) for c in ("mult", "uni_sumsq", "uni_l1"))), vectors)
    for name in ("lookup", "sharding"):
        add(f"joined_vectors_{name}", lambda s, d, n=name: attach(WORKLOADS["embeddings"](s, d), M.cosine("vector"), M.cosine("vector", norm="l1"), joining=n, C=20).select("entity", "element", *(F.round(c, 6).alias(c) for c in ("mult", "uni_sumsq", "uni_l1"))), vectors)
    for combiner in ("partition", "none"):
        add(f"joined_combiner_{combiner}", lambda s, d, c=combiner: attach_online(WORKLOADS[w](s, d), M.ruzicka(), impl="tagged" if c == "partition" else "smj", combiner=c).select("entity", "element", "mult", "uni_card"), sql)


def _measures() -> None:
    for m in ("jaccard", "ruzicka", "dice_set", "dice_multiset", "cosine_set", "cosine_multiset", "overlap_coefficient", "containment", "tversky", "tanimoto"):
        add(f"pairs_{m}_doc_shingles", _pairs("doc_shingles", m, 0.5), oracles.pairs("doc_shingles", m, 0.5))
    for m, w, t in (("jaccard", "order_parts", 0.5), ("dice_multiset", "conv_words", 0.5), ("cosine_multiset", "page_words", 0.7), ("ruzicka", "user_props", 0.3), ("ruzicka", "supp_parts", 0.1), ("ruzicka", "cust_parts", 0.1), ("ruzicka", "page_words", 0.5), ("jaccard", "doc_words", 0.5)):
        add(f"pairs_{m}_{w}", _pairs(w, m, t, **({"similarity": "blocks", "prune": True} if w == "doc_words" else {})), oracles.pairs(w, m, t))
    add("pairs_cosine_vector_user_props", _pairs("user_props", M.cosine("vector"), 0.6), oracles.pairs("user_props", "cosine_vector", 0.6))
    add("pairs_cosine_signed_embeddings", _pairs("embeddings", M.cosine("vector", signed=True), 0.3, similarity="blocks"), oracles.pairs("embeddings", "cosine_signed", 0.3))
    add("pairs_cosine_magnitudes_embeddings", _pairs("embeddings", M.cosine("vector"), 0.75, similarity="blocks"), oracles.pairs("embeddings", "cosine_vector", 0.75))
    add("pairs_cosine_l1_user_props", _pairs("user_props", M.cosine("vector", norm="l1"), 0.012), oracles.pairs("user_props", "cosine_vector_l1", 0.012))
    for m, t in (("overlap", 100), ("inner_product", 200), ("union_size", 2000)):
        add(f"pairs_{m}_doc_shingles", _pairs("doc_shingles", m, t), oracles.pairs("doc_shingles", m, t))
    add("pairs_symmetric_difference_doc_shingles", _pairs("doc_shingles", "symmetric_difference", 60), oracles.pairs("doc_shingles", "symmetric_difference", 60, distance=True))
    add("pairs_bray_curtis_doc_shingles", _pairs("doc_shingles", "bray_curtis", 0.5), oracles.pairs("doc_shingles", "bray_curtis", 0.5, distance=True))
    add("pairs_squared_l2_user_props", _pairs("user_props", "squared_l2", 90), oracles.pairs("user_props", "squared_l2", 90, distance=True))
    weights = f"WITH r AS MATERIALIZED ({RAW_SQL['doc_shingles']}), n AS (SELECT count(DISTINCT entity) AS n FROM r), f AS (SELECT element, count(*) AS f FROM r GROUP BY element) SELECT entity, element, round(ln(n / f) * 1000000)::BIGINT AS mult FROM r JOIN f USING (element), n WHERE f < n"
    add("pairs_weighted_jaccard_idf_doc_shingles", lambda s, d: _rounded(similarity_join(idf_weighted(WORKLOADS["doc_shingles"](s, d)), "weighted_jaccard_idf", 0.5, unique=True)), oracles.pairs("doc_shingles", "ruzicka", 0.5, raw_sql=weights))

    def registered(s, d):
        """Kulczynski's measure, made of plain functions and known by name from then on."""
        M.register_measure(measure_of("kulczynski", {"n": lambda x, y: int(x > 0), "o": lambda x, y: int(x > 0 and y > 0)}, {"n": lambda f, g: (f > 0).cast("long"), "o": lambda f, g: ((f > 0) & (g > 0)).cast("long")}, lambda c, a, b: (c["o"].cast("double") / a["n"].cast("double") + c["o"].cast("double") / b["n"].cast("double")) / 2, digits=9))
        return _rounded(similarity_join(WORKLOADS["user_props"](s, d), "kulczynski", 0.4, unique=True))

    add("pairs_registered_measure_user_props", registered, oracles.pairs("user_props", "kulczynski", 0.4))
    rewritten = decompose_disjunctive("union_direct", lambda a, b: F.greatest(a, b))
    add("pairs_decomposed_union_supp_parts", _pairs("supp_parts", rewritten, 20000), oracles.pairs("supp_parts", "union_size", 20000))
    add("symdiff_direct_supp_parts", lambda s, d: disjunctive_sums(WORKLOADS["supp_parts"](s, d), similarity_join(WORKLOADS["supp_parts"](s, d), "overlap", 1, unique=True), lambda a, b: F.abs(a - b)).select("e1", "e2", F.col("value").cast("double").alias("sim")), oracles.pairs("supp_parts", "symmetric_difference", 1e12, distance=True))
    several = ["ruzicka", "jaccard", "dice_multiset", "cosine_set"]
    sims = {m: f"({oracles.scored('doc_shingles', m)}SELECT * FROM sims_)" for m in several}
    add("pairs_shared_partials_doc_shingles", lambda s, d: similarity_join(WORKLOADS["doc_shingles"](s, d), t=0.5, measures=several, unique=True).select("e1", "e2", *(F.round(f"sim_{m}", 9).alias(f"sim_{m}") for m in several)), f"SELECT a.e1, a.e2, {', '.join(f'{x}.sim AS sim_{m}' for x, m in zip('abcd', several))} FROM {sims[several[0]]} a " + " ".join(f"JOIN {sims[m]} {x} ON {x}.e1 = a.e1 AND {x}.e2 = a.e2" for x, m in list(zip("abcd", several))[1:]) + " WHERE a.sim >= CAST(0.5 AS DOUBLE)")


def _variants() -> None:
    for joining in ("online_aggregation", "lookup", "sharding"):
        for w, t in (("doc_shingles", 0.5), ("order_parts", 0.7), ("page_words", 0.7)):
            add(f"pairs_ruzicka_{joining}_{w}", _pairs(w, "ruzicka", t, joining=joining, C=500, **({"similarity": "blocks", "prune": True} if w == "page_words" else {})), oracles.pairs(w, "ruzicka", t))
    for inclusive in (True, False):
        add(f"pairs_{'inclusive' if inclusive else 'strict'}_order_parts", _pairs("order_parts", "ruzicka", 0.5, inclusive=inclusive), oracles.pairs("order_parts", "ruzicka", 0.5, inclusive))
    for w, joining in (("doc_shingles", "online_aggregation"), ("order_parts", "sharding"), ("user_props", "lookup")):

        def sweep(s, d, w=w, joining=joining):
            found = similarity_join(WORKLOADS[w](s, d), "ruzicka", STEPS[0], joining=joining, unique=True).select("sim")
            counts = found.agg(*(F.count(F.when(F.col("sim") >= t, 1)).alias(f"p{k}") for k, t in enumerate(STEPS)))
            return counts.select(F.explode(F.array(*(F.struct(F.lit(t).alias("t"), F.col(f"p{k}").alias("pairs")) for k, t in enumerate(STEPS)))).alias("x")).select("x.*")

        add(f"threshold_sweep_counts_{w}", sweep, oracles.sweep(w, "ruzicka", STEPS))
    add("pairs_stopwords_q50_page_words", _pairs("page_words", "ruzicka", 0.5, q=50), oracles.pairs("page_words", "ruzicka", 0.5, q=50))
    add("pairs_stopwords_bounded_page_words", _pairs("page_words", "ruzicka", 0.5, q=50, stopword_impl="bounded"), oracles.pairs("page_words", "ruzicka", 0.5, q=50))
    add("pairs_stopwords_index_only_page_words", _pairs("page_words", "ruzicka", 0.3, q=50, stopword_scope="index_only"), oracles.pairs("page_words", "ruzicka", 0.3, index_q=50))
    sql = oracles.pairs("doc_shingles", "ruzicka", 0.5)
    for t in (1, 4):
        add(f"pairs_chunked_t{t}", _pairs("doc_shingles", "ruzicka", 0.5, similarity="chunked", T=t), sql)
    add("pairs_chunked_by_size", _pairs("doc_shingles", "ruzicka", 0.5, similarity="chunked", max_list_rows=20), sql)
    add("pairs_chunked_flagged", _pairs("doc_shingles", "ruzicka", 0.5, similarity="chunked", T=3, freq_limit=30), sql)
    add("pairs_chunked_ordered", _pairs("doc_shingles", "ruzicka", 0.5, similarity="chunked", T=4, chunk_pairs="ordered"), sql)
    add("pairs_chunked_stopwords_page_words", _pairs("page_words", "ruzicka", 0.5, similarity="chunked", T=3, q=50), oracles.pairs("page_words", "ruzicka", 0.5, q=50))
    add("pairs_chunked_pruned_t4", _pairs("doc_shingles", "ruzicka", 0.5, similarity="chunked", T=4, prune=True), sql)
    add("pairs_chunked_pruned_page_words", _pairs("page_words", "cosine_multiset", 0.8, similarity="chunked", max_list_rows=50, prune=True), oracles.pairs("page_words", "cosine_multiset", 0.8))
    add("pairs_chunked_pruned_ordered", _pairs("doc_shingles", "ruzicka", 0.5, similarity="chunked", T=3, chunk_pairs="ordered", prune=True), sql)
    for w, m, t in (("doc_shingles", "ruzicka", 0.5), ("order_parts", "jaccard", 0.5), ("user_props", "ruzicka", 0.3)):
        add(f"pairs_auto_{w}", _pairs(w, m, t, similarity="auto", joining="auto"), oracles.pairs(w, m, t))
    add("pairs_auto_chunked_page_words", _pairs("page_words", "cosine_multiset", 0.8, similarity="auto", max_list_rows=64), oracles.pairs("page_words", "cosine_multiset", 0.8))
    add("pairs_list_index", _pairs("doc_shingles", "ruzicka", 0.5, similarity="list"), sql)
    add("pairs_aqe_skew", _pairs("doc_shingles", "ruzicka", 0.5, similarity="aqe"), sql)
    add("pairs_hash_index", _pairs("doc_shingles", "ruzicka", 0.5, hint="shuffle_hash"), sql)
    for carry in ("first", "rejoin"):
        add(f"pairs_carry_{carry}", _pairs("doc_shingles", "ruzicka", 0.5, carry=carry), sql)
    add("pairs_pruned_doc_shingles", _pairs("doc_shingles", "ruzicka", 0.5, prune=True), sql)
    add("pairs_banded_doc_shingles", _pairs("doc_shingles", "ruzicka", 0.5, prune="bands"), sql)
    add("pairs_banded_order_parts", _pairs("order_parts", "jaccard", 0.5, prune="bands"), oracles.pairs("order_parts", "jaccard", 0.5))
    add("pairs_pruned_page_words", _pairs("page_words", "cosine_multiset", 0.8, prune=True), oracles.pairs("page_words", "cosine_multiset", 0.8))
    add("pairs_relabelled_alphabet", lambda s, d: _rounded(similarity_join(shuffle_alphabet(WORKLOADS["doc_shingles"](s, d), 7), "ruzicka", 0.5, unique=True)), sql)
    add("pairs_min50_doc_shingles", _pairs("doc_shingles", "ruzicka", 0.1, min_elements=50), oracles.pairs("doc_shingles", "ruzicka", 0.1, min_elements=50))
    add("pairs_lookup_after_min50", _pairs("doc_shingles", "ruzicka", 0.5, min_elements=50, joining="lookup", max_table_bytes=1 << 20), oracles.pairs("doc_shingles", "ruzicka", 0.5, min_elements=50))
    add("pairs_both_directions", lambda s, d: _rounded(similarity_join(WORKLOADS["doc_shingles"](s, d), "ruzicka", 0.5, symmetric_output=True, unique=True)), f"SELECT e1, e2, sim FROM ({sql}) UNION ALL SELECT e2, e1, sim FROM ({sql})")
    rs = """WITH d AS (%s), b AS (%s), dn AS (SELECT entity, count(*) AS n FROM d GROUP BY 1), bn AS (SELECT entity, count(*) AS n FROM b GROUP BY 1),
    s AS (SELECT d.entity AS e1, b.entity AS e2, count(*) AS s FROM d JOIN b USING (element) GROUP BY ALL)
    SELECT e1, e2, round(s::DOUBLE / least(dn.n, bn.n)::DOUBLE, 9) AS sim FROM s JOIN dn ON dn.entity = e1 JOIN bn ON bn.entity = e2 WHERE s::DOUBLE / least(dn.n, bn.n)::DOUBLE >= CAST(0.5 AS DOUBLE)""" % (RAW_SQL["doc_shingles"], RAW_SQL["benchmark_shingles"])
    add("rs_contamination", lambda s, d: _rounded(similarity_join_rs(as_sets(WORKLOADS["doc_shingles"](s, d)), as_sets(WORKLOADS["benchmark_shingles"](s, d)), "overlap_coefficient", 0.5, unique=True)), rs)
    half = oracles.pairs("doc_shingles", "ruzicka", 0.1)
    add("topk_overall_doc_shingles", lambda s, d: _rounded(top_k(_rounded(similarity_join(WORKLOADS["doc_shingles"](s, d), "ruzicka", 0.1, unique=True)), 20, False)), f"SELECT * FROM ({half}) ORDER BY sim DESC, e1, e2 LIMIT 20")
    add("topk_per_entity_doc_shingles", lambda s, d: top_k(_rounded(similarity_join(WORKLOADS["doc_shingles"](s, d), "ruzicka", 0.1, unique=True)), 3), f"SELECT entity, other, sim, rank FROM (SELECT *, (row_number() OVER (PARTITION BY entity ORDER BY sim DESC, other))::INTEGER AS rank FROM (SELECT e1 AS entity, e2 AS other, sim FROM ({half}) UNION ALL SELECT e2, e1, sim FROM ({half}))) WHERE rank <= 3")


def _baselines() -> None:
    def prefix(w: str, m: M.Measure, t: float, **options) -> Query:
        return lambda s, d: _rounded(prefix_replication(WORKLOADS[w](s, d), m, t, **options))

    for name, options in (("frequency", {}), ("hash", {"order": "hash"}), ("grouped", {"grouping": 1024}), ("indexed", {"kernel": "indexed"}), ("distinct", {"dedup": "distinct"}), ("no_length_filter", {"filters": ()})):
        add(f"baseline_prefix_{name}_order_parts", prefix("order_parts", M.jaccard(), 0.5, **options), oracles.pairs("order_parts", "jaccard", 0.5))
    add("baseline_prefix_frequency_doc_shingles", lambda s, d: _rounded(prefix_replication(WORKLOADS["doc_shingles"](s, d, dealt=True), M.jaccard(), 0.9, kernel="blocks")), oracles.pairs("doc_shingles", "jaccard", 0.9))
    add("baseline_prefix_multiset_order_parts", prefix("order_parts", M.ruzicka(), 0.7), oracles.pairs("order_parts", "ruzicka", 0.7))
    for m in ("dice_set", "cosine_set"):
        add(f"baseline_prefix_{m}_order_parts", prefix("order_parts", M.by_name(m), 0.7), oracles.pairs("order_parts", m, 0.7))
    add("baseline_prefix_jaccard_doc_words", prefix("doc_words", M.jaccard(), 0.8), oracles.pairs("doc_words", "jaccard", 0.8))

    def with_records(s, d):
        raw = WORKLOADS["doc_shingles"](s, d)
        pairs = prefix_replication(raw, M.jaccard(), 0.9)
        return rejoin_records(pairs, records(raw)).select("e1", "e2", F.size("items1").cast("long").alias("n1"), F.size("items2").cast("long").alias("n2"))

    add("baseline_prefix_records_doc_shingles", with_records, f"SELECT e1, e2, a.n AS n1, b.n AS n2 FROM ({oracles.pairs('doc_shingles', 'jaccard', 0.9)}) JOIN (SELECT entity, count(*) AS n FROM ({RAW_SQL['doc_shingles']}) GROUP BY 1) a ON a.entity = e1 JOIN (SELECT entity, count(*) AS n FROM ({RAW_SQL['doc_shingles']}) GROUP BY 1) b ON b.entity = e2")
    add("baseline_brute_supp_parts", lambda s, d: _rounded(brute_force(WORKLOADS["supp_parts"](s, d), M.ruzicka(), 0.1)), oracles.pairs("supp_parts", "ruzicka", 0.1))
    def late(s, d):
        raw, near = _near_shingles(s, d, "ruzicka", 0.5)
        return _rounded(late_join(raw, M.ruzicka(), 0.5, near=near))

    add("baseline_late_join_doc_shingles", late, oracles.pairs("doc_shingles", "ruzicka", 0.5))
    add("baseline_disjunctive_supp_parts", lambda s, d: _rounded(ruzicka_disjunctive(WORKLOADS["supp_parts"](s, d), 0.1)), oracles.pairs("supp_parts", "ruzicka", 0.1))

    def lsh(s, d):
        raw, near = _near_shingles(s, d, "jaccard", 0.5)
        return recall_precision(minhash_lsh(raw, M.jaccard(), 0.5, 24, 3, near=near), similarity_join(raw, "jaccard", 0.5, unique=True, near=near))

    add("lsh_recall_doc_shingles", lsh)


def _graphs_and_quality() -> None:
    for w, t in (("doc_shingles", 0.5), ("order_parts", 0.7)):
        sql = oracles.pairs(w, "ruzicka", t)

        def grouped(s, d, w=w, t=t):
            raw, near = _near_shingles(s, d, "ruzicka", t) if w == "doc_shingles" else (WORKLOADS[w](s, d), None)
            return communities(similarity_join(raw, "ruzicka", t, unique=True, near=near))

        add(f"communities_{w}", grouped, oracles.components(sql))

    def report(s, d):
        raw = WORKLOADS["doc_shingles"](s, d)
        return quality.community_report(communities(similarity_join(raw, "ruzicka", 0.5, unique=True)), raw)

    add("community_report_doc_shingles", report, f"SELECT *, (row_number() OVER (ORDER BY entities DESC, community))::INTEGER AS place FROM (SELECT community, count(DISTINCT c.entity)::BIGINT AS entities, count(*)::BIGINT AS rows, sum(mult)::BIGINT AS copies FROM ({oracles.components(oracles.pairs('doc_shingles', 'ruzicka', 0.5))}) c JOIN ({RAW_SQL['doc_shingles']}) r ON r.entity = c.entity GROUP BY community ORDER BY entities DESC, community LIMIT 7)")
    for w, table, key, value, m, t in (("doc_shingles", "documents", "doc_id", "lang", M.ruzicka(), "ruzicka"), ("embeddings", "embeddings", "vec_id", "label", M.cosine("vector", signed=True), "cosine_signed")):
        low = 0.1 if w == "doc_shingles" else 0.3
        steps = [0.1, 0.3, 0.5, 0.9] if w == "doc_shingles" else [0.3, 0.4]

        def judged(s, d, w=w, table=table, key=key, value=value, m=m, low=low, steps=steps):
            evidence = read_table(s, d, table, [key, value]).select(F.col(key).alias("entity"), F.col(value).alias("value"))
            return quality.quality_sweep(_rounded(similarity_join(WORKLOADS[w](s, d), m, low, unique=True, similarity="blocks" if w == "embeddings" else "index")), evidence, steps)

        one = " UNION ALL ".join(f"SELECT CAST({x} AS DOUBLE) AS t, (SELECT count(*) FROM p WHERE sim >= {x}) AS pairs, (SELECT count(*) FROM (SELECT e1 FROM p WHERE sim >= {x} UNION SELECT e2 FROM p WHERE sim >= {x})) AS covered, (SELECT count(*) FROM p JOIN {table} a ON a.{key} = e1 JOIN {table} b ON b.{key} = e2 WHERE sim >= {x} AND a.{value} <> b.{value}) AS differ" for x in steps)
        add(f"coverage_fp_{w}", judged, f"WITH p AS MATERIALIZED ({oracles.pairs(w, t, low)}) {one}")
    p = oracles.pairs("doc_shingles", "ruzicka", 0.1)

    def sampled(s, d):
        evidence = read_table(s, d, "documents", ["doc_id", "lang"]).select(F.col("doc_id").alias("entity"), F.col("lang").alias("value"))
        return quality.false_positive_rate(similarity_join(WORKLOADS["doc_shingles"](s, d), "ruzicka", 0.1, unique=True), evidence, sample_of=2)

    differ = "(count(*) FILTER (WHERE a.lang <> b.lang))::BIGINT"
    add("false_positive_sampled_doc_shingles", sampled, f"SELECT count(*) AS pairs, {differ} AS differ, round({differ}::DOUBLE / greatest(count(*), 1), 9) AS rate FROM ({p}) JOIN documents a ON a.doc_id = e1 JOIN documents b ON b.doc_id = e2 WHERE substr(md5(e1 || ':' || e2 || ':0'), 1, 4) < '8000'")
    add("coverage_min50_doc_shingles", lambda s, d: quality.coverage(similarity_join(WORKLOADS["doc_shingles"](s, d), "ruzicka", 0.1, min_elements=50, unique=True)), f"WITH p AS ({oracles.pairs('doc_shingles', 'ruzicka', 0.1, min_elements=50)}) SELECT count(*)::BIGINT AS covered FROM (SELECT e1 FROM p UNION SELECT e2 FROM p)")
    add("coverage_doc_shingles", lambda s, d: quality.coverage(similarity_join(WORKLOADS["doc_shingles"](s, d), "ruzicka", 0.1, unique=True)), f"WITH p AS ({oracles.pairs('doc_shingles', 'ruzicka', 0.1)}) SELECT count(*)::BIGINT AS covered FROM (SELECT e1 FROM p UNION SELECT e2 FROM p)")
    add("profile_ratio_doc_words", lambda s, d: quality.profile_ratio(WORKLOADS["doc_words"](s, d)), f"SELECT round(count(DISTINCT element)::DOUBLE / count(DISTINCT entity), 9) AS ratio FROM ({RAW_SQL['doc_words']})")


def _costs() -> None:
    f = "SELECT element, count(*)::BIGINT AS f FROM (%s) GROUP BY element"
    for w in ("doc_words", "doc_shingles", "order_parts", "page_words"):
        one = "coalesce(sum(f * (f - 1) // 2), 0)::BIGINT AS increments, max(f)::BIGINT AS longest_list, max(f * (f - 1) // 2)::BIGINT AS slowest_task, max(ceil(f / {T}))::BIGINT AS longest_chunk, sum(f * {T})::BIGINT AS rows_shipped"
        add(f"cost_index_{w}", lambda s, d, w=w: costs.index_cost(WORKLOADS[w](s, d)), f"SELECT {one.replace('{T}', '1')} FROM ({f % RAW_SQL[w]})")
        add(f"cost_index_q50_t4_{w}", lambda s, d, w=w: costs.index_cost(WORKLOADS[w](s, d), 50, 4), f"SELECT {one.replace('{T}', '4')} FROM ({f % RAW_SQL[w]}) WHERE f <= 50")
        add(f"cost_joining_{w}", lambda s, d, w=w: costs.joining_cost(WORKLOADS[w](s, d)), f"SELECT count(*)::BIGINT AS entities, max(n)::BIGINT AS largest_entity, sum(n)::BIGINT AS rows FROM (SELECT count(*) AS n FROM ({RAW_SQL[w]}) GROUP BY entity)")
    limits = [1 << k for k in range(5, 16)]
    add("cost_lookup_footprint_sweep", lambda s, d: costs.lookup_footprint(WORKLOADS["doc_shingles"](s, d), limits), f"SELECT l.c AS \"limit\", count(n)::BIGINT AS entries FROM (SELECT unnest({limits})::BIGINT AS c) l LEFT JOIN (SELECT count(*) AS n FROM ({RAW_SQL['doc_shingles']}) GROUP BY entity) ON n > l.c GROUP BY l.c")
    for t in (0.1, 0.5, 0.9):
        add(f"cost_replication_t{int(t * 10)}_doc_words", lambda s, d, t=t: replication_cost(WORKLOADS["doc_words"](s, d), M.jaccard(), t), f"SELECT sum((n - ceil(n * CAST({t} AS DOUBLE) - 1e-9)::BIGINT + 1) * n)::BIGINT AS cells FROM (SELECT count(*) AS n FROM ({RAW_SQL['doc_words']}) GROUP BY entity)")
    shared = f"WITH r AS MATERIALIZED ({RAW_SQL['doc_shingles']}) SELECT count(*)::BIGINT AS n, max(c)::BIGINT AS m FROM (SELECT count(*) AS c FROM r a JOIN r b ON a.element = b.element AND a.entity < b.entity GROUP BY a.entity, b.entity)"
    add("cost_max_intersection_doc_shingles", lambda s, d: costs.max_intersection(WORKLOADS["doc_shingles"](s, d)), f"SELECT n AS candidates, m AS longest_intersection FROM ({shared})")
    add("cost_selectivity_doc_shingles", lambda s, d: costs.selectivity(pair_increments(WORKLOADS["doc_shingles"](s, d)).select("e1", "e2").distinct(), similarity_join(WORKLOADS["doc_shingles"](s, d), "ruzicka", 0.5, unique=True)), f"SELECT (SELECT n FROM ({shared})) AS candidates, (SELECT count(*) FROM ({oracles.pairs('doc_shingles', 'ruzicka', 0.5)})) AS results")

    def stats(s, d):
        x = planner.statistics(WORKLOADS["page_words"](s, d))
        return s.createDataFrame([(x.rows, x.entities, x.elements, x.largest_entity, x.highest_freq, x.increments)], "rows long, entities long, elements long, largest_entity long, highest_freq long, increments long")

    add("planner_statistics_page_words", stats, f"WITH r AS MATERIALIZED ({RAW_SQL['page_words']}), f AS ({f % 'SELECT * FROM r'}), e AS (SELECT count(*) AS n FROM r GROUP BY entity) SELECT (SELECT count(*) FROM r) AS rows, (SELECT count(*) FROM e) AS entities, (SELECT count(*) FROM f) AS elements, (SELECT max(n) FROM e) AS largest_entity, (SELECT max(f) FROM f) AS highest_freq, (SELECT sum(f * (f - 1) // 2)::BIGINT FROM f) AS increments")


for _part in (_totals_and_profiles, _joining, _measures, _variants, _baselines, _graphs_and_quality, _costs):
    _part()


def queries() -> dict[str, Query]:
    from . import operators, streaming

    return _QUERIES | operators.queries() | streaming.queries()


def oracle_sql() -> dict[str, str]:
    from . import operators, streaming

    return _SQL | operators.oracle_sql() | streaming.oracle_sql()
