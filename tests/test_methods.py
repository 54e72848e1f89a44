"""Worked examples, brute force and invariants of the methods."""

import itertools
from datetime import datetime, timedelta

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from kbspark.functions import finance as ff
from kbspark.operators import dictionary, extract, fusion, graph, lexical, measure, profile, records, rowmatch, serve, synth, vectors
from kbspark.sources.tables import table


def weight(p, g, beta=2.0):
    p, g = set(p), set(g)
    c = len(p & g)
    if not c:
        return 0.0
    pre, rec = c / len(p), c / len(g)
    return (1 + beta**2) * pre * rec / (beta**2 * pre + rec)


def edges(P, G, beta=2.0):
    found = [(i, j, weight(p, g, beta)) for i, p in enumerate(P) for j, g in enumerate(G) if weight(p, g, beta)]
    i, j, w = zip(*found, strict=True) if found else ((), (), ())
    return np.array(i, int), np.array(j, int), np.array(w, float)


def brute_unordered(P, G, beta=2.0):
    small, large = (P, G) if len(P) <= len(G) else (G, P)
    w = (lambda a, b: weight(a, b, beta)) if small is P else (lambda a, b: weight(b, a, beta))
    return max((sum(w(s, large[k]) for s, k in zip(small, perm, strict=True)) for perm in itertools.permutations(range(len(large)), len(small))), default=0.0)


def brute_ordered(P, G, beta=2.0):
    best = np.zeros((len(P) + 1, len(G) + 1))
    for i, p in enumerate(P):
        for j, g in enumerate(G):
            best[i + 1, j + 1] = max(best[i, j + 1], best[i + 1, j], best[i, j] + weight(p, g, beta))
    return best[-1, -1]


rows = st.lists(st.lists(st.sampled_from("abcd"), min_size=1, max_size=3), max_size=5)


@settings(max_examples=150, deadline=None)
@given(rows, rows)
def test_row_matching(P, G):
    assert abs(rowmatch.best_unordered(*edges(P, G)) - brute_unordered(P, G)) < 1e-9
    assert abs(rowmatch.best_ordered(*edges(P, G)) - brute_ordered(P, G)) < 1e-9


def test_row_weight_example():
    assert abs(weight("abc", "ab") - 10 / 11) < 1e-12
    P, G = ["ab", "a"], ["ab", "b"]
    assert abs(rowmatch.best_unordered(*edges(P, G, 1.0)) - 4 / 3) < 1e-9  # taking out the equal pair first gives 1


def test_scores(spark):
    mk = lambda rows: spark.createDataFrame([("c", i, list(r)) for i, r in enumerate(rows)], "case string, row_no long, cells array<string>")
    s = lambda p, g, o=False: rowmatch.score(mk(p), mk(g), o).first()["score"]
    g = [("a", "1"), ("b", "2"), ("c", "3")]
    assert s(g, g) == 1 and s([r[::-1] for r in g], g) == 1 and s(g[::-1], g) == 1
    assert s(g[::-1], g, True) == round(1 / 3, 6)
    assert s([*g, ("x", "y")], g) == 0.75
    assert s([(*r, "new") for r in g], g) == round(10 / 11, 6)


def test_components_give_the_same_score(spark):
    rng = np.random.default_rng(4)
    mk = lambda seed: spark.createDataFrame([(c, i, [str(x) for x in rng.integers(0, 60, 2)]) for c in "ab" for i in range(40)], "case string, row_no long, cells array<string>")
    p, g = mk(1), mk(2)
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert rows(rowmatch.score(p, g)) == rows(rowmatch.score(p, g, large=10))


def test_cascade_and_vote(spark):
    mk = lambda rows: spark.createDataFrame([(1, t, n, "error" if x == "E" else "ok", None if x == "E" else x, 10) for t, n, x in rows], "q_id long, tier int, sample_no int, status string, fp string, latency_ms long")
    assert serve.vote(mk([(1, i, x) for i, x in enumerate("aabEbb")])).first()[1:] == ("b", 3)
    assert serve.vote(mk([(1, 0, "E"), (1, 1, "E")])).count() == 0
    r = serve.cascade(mk([(1, 1, "a"), (1, 2, "b"), (2, 1, "b"), (2, 2, "c"), (3, 1, "z")])).first()
    assert (r["fp"], r["tier"], r["samples_used"], r["agreed"]) == ("b", 2, 3, True)
    r = serve.cascade(mk([(1, 1, "a"), (1, 2, "a"), (2, 1, "b"), (2, 2, "b")])).first()
    assert (r["fp"], r["tier"], r["samples_used"]) == ("a", 1, 2)


def test_voting_and_cascade_orders(spark):
    """Which method wins: more votes beat one sample; the cascade spends fewer samples; no knowledge base is worst."""
    import __spark_entry__ as e

    sf = "/root/testdata/sf0.001"
    ex = {k: e.QUERIES[k](spark, sf).first()["ex"] for k in ("ex_schema_only", "ex_n1", "ex_n8_vote")}
    assert ex["ex_schema_only"] < ex["ex_n1"] < ex["ex_n8_vote"]
    assert e.QUERIES["cascade_cost"](spark, sf).first()["samples"] < 8


def naive(patterns, tokens):
    return sorted((k, i, i + len(p)) for k, (_, p) in enumerate(patterns) if p for i in range(len(tokens) - len(p) + 1) if tokens[i : i + len(p)] == p)


@settings(max_examples=150, deadline=None)
@given(st.lists(st.lists(st.sampled_from("abc"), min_size=1, max_size=4), min_size=1, max_size=8), st.lists(st.sampled_from("abcd"), max_size=20))
def test_automaton(pats, tokens):
    patterns = list(enumerate(pats))
    for kind in ("double", "trie"):
        assert sorted(dictionary.Automaton(patterns, kind).matches(tokens)) == naive(patterns, tokens)


def test_automaton_characters_and_tokens(spark):
    a = dictionary.Automaton([(k, list(p)) for k, p in enumerate(("he", "she", "hers"))])
    assert sorted(a.matches(list("ushers"))) == [(0, 2, 4), (1, 1, 4), (2, 2, 6)]
    syn = spark.createDataFrame([("r", "art")], "record_id string, synonym string")
    docs = spark.createDataFrame([(1, "part art"), (2, ""), (3, None)], "id long, t string")
    hit = dictionary.match(docs, "id", "t", dictionary.build(syn)).collect()
    assert [(h["id"], h["start"], h["stop"]) for h in hit] == [(1, 5, 8)]
    assert dictionary.match(docs, "id", "t", dictionary.build(syn.limit(0))).count() == 0
    big = dictionary.Automaton([(i, [f"w{i}", f"w{i + 1}"]) for i in range(2000)])
    assert big.bytes() < dictionary.Automaton([(i, [f"w{i}", f"w{i + 1}"]) for i in range(2000)], "trie").bytes()


def test_merge_example(spark):
    rec = lambda rows: spark.createDataFrame(rows, "record_id string, content_hash string, synonyms array<string>, priority int")
    kb = rec([("r1", "A", ["x"], 5)]).withColumn("trusted", F.lit(True))
    new = [("r1", "A", ["y"], 5), ("r2", "B", [], 5), ("r2", "C", [], 5), ("r3", "D", [], 5), ("r1", "E", [], 5)]
    for order in (new, new[::-1]):
        merged, rejects = records.merge_records(kb, rec(order))
        got = {r["record_id"]: (r["synonyms"], r["priority"]) for r in merged.collect()}
        assert got == {"r1": (["x", "y"], 5), "r3": ([], 4)}
        assert sorted((r[0], r[1]) for r in rejects.collect()) == [("r1", "E"), ("r2", "B"), ("r2", "C")]
    again, rejects = records.merge_records(merged, rec([("r1", "A", ["y"], 5)]))
    assert {r["record_id"] for r in again.collect()} == {"r1", "r3"} and rejects.count() == 0


def test_lifecycle(spark):
    t = datetime(2025, 1, 1)
    df = spark.createDataFrame([(i, t, t, e, False) for i, e in enumerate((-1, 0, 10))], "record_id int, timestamp timestamp, last_verified timestamp, expiration long, inactive_mark boolean")
    alive = lambda d, s: sorted(r[0] for r in records.active(d, F.lit(t + timedelta(seconds=s))).select("record_id").collect())
    assert alive(df, 5) == [0, 2] and alive(df, 11) == [0]
    renewed = records.verify(df, df.where("record_id = 2"), F.lit(t + timedelta(seconds=8)))
    assert alive(renewed, 11) == [0, 2]
    assert alive(records.retire(df, df.where("record_id = 0")), 5) == [2]


def test_identity_and_slots(spark):
    made = lambda tags: records.with_slots(records.new(spark.createDataFrame([("n", "c", tags)], "name string, content string, tags array<string>"), "knowledge")).first()
    a, b = made(["[ENUM:operational]", "[COLUMN:status]", "[COLUMN:state]"]), made(["[COLUMN:state]", "[COLUMN:status]", "[ENUM:operational]"])
    assert a["record_id"] == b["record_id"] and a["slots"] == {"COLUMN": ["state", "status"], "ENUM": ["operational"]}
    with pytest.raises(ValueError):
        records.new(spark.createDataFrame([("n", "c")], "name string, content string"), "enum")


def test_triggers(spark):
    df = spark.createDataFrame([(1, "lower(x) = 'a'", "A"), (2, "lower(x) = 'a'", "B"), (3, None, "C")], "id int, trigger string, x string")
    assert [r[0] for r in records.apply_triggers(df).orderBy("id").collect()] == [1, 3]
    for bad in ("x IN (SELECT 1)", "java_method('a','b')", "1=1; drop table t"):
        assert not records.trigger_ok(bad)


def test_latest_and_variant(spark):
    df = spark.createDataFrame([("a", "v0.2.0", "default"), ("a", "v0.10.0", "default"), ("a", "v0.10.0b", "fr")], "name string, version string, variant string")
    assert records.latest(df, ["name"]).first()["version"] == "v0.10.0b"
    assert records.variant(df, "de", ["name"]).first()["variant"] == "default" and records.variant(df, "fr", ["name"]).first()["variant"] == "fr"


def test_containment_example(spark):
    k = spark.createDataFrame([("asia",)], "keyword string")
    v = spark.createDataFrame([("asian",), ("eurasia",), ("asi",)], "value string")
    got = {r["value"]: r["score"] for r in lexical.containment(k, v).collect()}
    assert got == {"asian": 1.0, "eurasia": 1.0, "asi": 0.5}


def test_round_robin_example(spark):
    lists = spark.createDataFrame([(1, 1, i, x) for i, x in enumerate("abc", 1)] + [(1, 2, i, x) for i, x in enumerate("bd", 1)], "q long, index_no int, rank int, id string")
    assert [r["id"] for r in fusion.round_robin(lists, 5).orderBy("rank").collect()] == ["a", "b", "d", "c"]


def test_vectors(spark, sf):
    base = table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
    q = base.where("id < 20").withColumnRenamed("id", "q")
    exact = vectors.knn(q, base, 10)
    as_rows = lambda df: sorted((r["q"], r["rank"], r["id"]) for r in df.collect())
    cells = vectors.cells(base, 8)
    assert as_rows(vectors.ann(q, base, 10, 4, 4)) == as_rows(exact) == as_rows(vectors.ivf(q, base, 10, cells, 8))
    assert measure.neighbour_recall(vectors.ivf(q, base, 10, cells, 6), exact).first()[0] >= 0.9
    near = exact.select("q", "id", "score").join(base, "id")
    plain = vectors.mmr(near, 5, 1.0)
    assert as_rows(plain) == as_rows(exact.where("rank <= 5"))


def test_graph_cycle(spark):
    e = spark.createDataFrame([("a", "r", "b"), ("b", "r", "a"), ("b", "r", "c"), ("c", "x", "d")], "subject string, relation string, object string")
    got = {(r["id"], r["hop"]) for r in graph.hops(e, spark.createDataFrame([("a",)], "seed string"), ["r"], 5).collect()}
    assert got == {("a", 0), ("b", 1), ("c", 2)}


def test_periods_and_growth(spark):
    one = lambda c: spark.range(1).select(c).first()[0]
    at = lambda s: F.lit(s).cast("timestamp")
    assert one(ff.current_period(at("2025-05-09"))) == "202504" and one(ff.current_period(at("2025-05-10"))) == "202505" and one(ff.current_period(at("2025-01-02"))) == "202412"
    for (a, b), want in {(0.0, 5.0): 0, (-4.0, 2.0): 1.5, (4.0, 2.0): -0.5, (None, 3.0): 0}.items():
        assert one(ff.growth(F.lit(b), F.lit(a).cast("double"))) == want


def test_time_formats(spark):
    df = spark.createDataFrame([("31/12/2024",), ("01/02/2024",)], "s string")
    got = {r["format"]: r["share"] for r in profile.time_formats(df, "s", ["dd/MM/yyyy", "MM/dd/yyyy"]).collect()}
    assert got == {"dd/MM/yyyy": 1.0, "MM/dd/yyyy": 0.5}


def test_published_error_shares(spark):
    from kbspark.workloads.serve_queries import PRINTED, error_shares

    printed = spark.createDataFrame(PRINTED, "difficulty string, share double, ex double")
    got = {r["difficulty"]: (r["error_share"], r["diff"]) for r in error_shares(printed).collect()}
    assert got == {"simple": (19.5, -10.3), "moderate": (52.2, 2.5), "challenging": (28.3, 7.8)}


def test_published_ranks(spark):
    from kbspark.workloads.serve_queries import PUBLISHED, ranked_accuracies

    made = ranked_accuracies(spark.createDataFrame(PUBLISHED, "dataset string, row_no int, n int, ex double"))
    got = {(r["dataset"], r["row_no"]): (r["rank"], r["gap"]) for r in made.collect()}
    assert got["first", 8] == (1, 0.0) and got["first", 1] == (8, 4.03) and got["second", 5] == (3, 4.8)


def test_error_causes_count_questions(spark, sf):
    """n against DuckDB running the same statements for every question."""
    import __spark_entry__ as e
    import duckdb
    from kbspark.workloads.questions import RESULTS_SQL

    con = duckdb.connect()
    con.execute("SET TimeZone='UTC'")
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    want = con.execute(f"""WITH {RESULTS_SQL} SELECT a.template || v.variant, count(*) FILTER (c.fp IS DISTINCT FROM g.fp) FROM asked a CROSS JOIN (VALUES ('a'), ('b'), ('d')) v(variant)
        LEFT JOIN cand c ON c.template = a.template AND c.variant = v.variant AND c.p = a.p AND c.r = a.r LEFT JOIN gold g ON g.template = a.template AND g.p = a.p AND g.r = a.r GROUP BY ALL""").fetchall()
    assert {r["mutation"]: r["n"] for r in e.QUERIES["error_causes"](spark, sf).collect()} == dict(want)


def test_commented_sql(spark, sf):
    synth.views(spark, sf, ["orders"])
    sql = "SELECT o_orderstatus, count(*) AS n FROM orders WHERE o_totalprice > 5 GROUP BY o_orderstatus ORDER BY n"
    for level in ("full", "basic"):
        assert synth.same_plan(spark, synth.strip(synth.profile(spark, "q?", sql, level=level)), sql)
    assert "result: o_orderstatus string, n bigint" in synth.profile(spark, "q?", sql)


def test_causes(spark):
    want = {"drop_predicate": "predicate", "add_predicate": "predicate", "swap_enum": "enum", "swap_column": "column", "bad_format": "format", "extra_column": "columns", "drop_distinct": "distinct", "no_limit": "ties", "syntax": "invalid", "same": "same"}
    want |= {"ratio_as_percent": "ratio", "other_unit": "ratio", "sum_for_avg": "computation", "null_kept": "null", "null_dropped": "null", "concatenated": "concat"}
    got = {op: measure.classify(extract.facts(spark, g) + extract.calls(spark, g), extract.facts(spark, b) + extract.calls(spark, b)) for op, g, b in synth.mutations()}
    assert got == want


def test_execute_and_refine(spark, sf):
    synth.views(spark, sf, ["orders"])
    r = serve.execute_sql(spark, "SELECT o_orderkey FROM orders", max_rows=3)
    assert r["status"] == "ok" and len(r["rows"]) == 3 and r["cut"] and r["total"] == table(spark, sf, "orders").count()
    assert serve.execute_sql(spark, "SELECT nope FROM orders")["error_class"].startswith("UNRESOLVED_COLUMN")
    fixed, trail = serve.refine(spark, "SELECT count(o_ordrstatus) FROM orders", ["o_orderstatus", "o_orderkey", "orders"])
    assert "o_orderstatus" in fixed and trail[-1] == "ok"


def test_definitions_and_pages(spark):
    docs = spark.createDataFrame([(1, "margin = revenue - cost\nGMV means gross value\nnoise\nhead office, also called HQ.")], "doc_id long, text string")
    assert {(r["kind"], r["name"]) for r in extract.definitions(docs).collect()} == {("formula", "margin"), ("meaning", "GMV"), ("alias", "head office")}
    pages = spark.createDataFrame([(1, "<style>x</style><h1>A&amp;B</h1><p>c<br>d</p><script>1<2</script>")], "page_id long, html string")
    assert extract.page_text(pages).first()["text"] == "A&B\nc\nd"
