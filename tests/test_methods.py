"""Worked examples, brute force and edge cases of the methods."""

import collections
import itertools
import math
import os
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from reportgraph.functions import text as T
from reportgraph.functions import vectors
from reportgraph.operators import graph, labeling, metrics, patterns, propagate, relations, titles, triage
from reportgraph.operators.components import connected_components
from reportgraph.operators.hot import join_hot
from reportgraph.operators.ranges import range_edges, range_of
from reportgraph.plans import mining
from reportgraph.tagger import crf, model, train


def test_npmi_examples(spark):
    for r in mining.QUERIES["npmi_golden"][0](spark, "").collect():
        assert abs(r["npmi"] - r["printed"]) <= 0.0101


def test_npmi_bounds(spark):
    rows = spark.createDataFrame([(5, 5, 5, 5), (4, 4, 4, 100), (10, 10, 1, 100)], "f1 long, f2 long, f_joint long, total long")
    got = [r["npmi"] for r in relations.score(rows).collect()]
    assert got[0] == 1.0 and got[1] == pytest.approx(1.0) and got[2] == pytest.approx(0.0)


def test_sketch_cliques(spark):
    got = {tuple(r["members"]) for r in graph.maximal_cliques(mining.sketch(spark)).collect()}
    assert got == {("network id", "network name", "network region"), ("gateway id", "network id", "network name"), ("network id", "network name", "subscription id"), ("gateway id", "tunnel name"), ("encap type", "tunnel name")}


def test_cliques_by_enumeration(spark):
    rng = random.Random(3)
    edges = [(a, b, rng.random()) for a, b in itertools.combinations(range(9), 2) if rng.random() < 0.5]
    has = {frozenset(e[:2]) for e in edges}
    sets = [s for n in range(2, 10) for s in itertools.combinations(range(9), n) if all(frozenset(p) in has for p in itertools.combinations(s, 2))]
    want = {s for s in sets if not any(set(s) < set(t) for t in sets)}
    got = {tuple(r["members"]) for r in graph.maximal_cliques(spark.createDataFrame(edges, "src long, dst long, weight double")).collect()}
    assert got == want


def test_sketch_paths(spark):
    p = graph.shortest_paths(mining.sketch(spark), spark.createDataFrame([("network id",)], "source string"))
    hops = {r["target"]: r["hops"] for r in p.collect()}
    assert hops == {"network id": 0, "network region": 1, "network name": 1, "subscription id": 1, "gateway id": 1, "tunnel name": 2, "encap type": 3}


def test_components_by_search(spark):
    rng = random.Random(5)
    edges = [(rng.randrange(80), rng.randrange(80)) for _ in range(60)] + [(None, 3), (4, 4)]
    parent = {v: v for e in edges for v in e if v is not None}

    def root(v):
        while parent[v] != v:
            v = parent[v]
        return v

    for a, b in edges:
        if a is not None and b is not None:
            x, y = root(a), root(b)
            parent[max(x, y)] = min(x, y)
    touched = {v for a, b in edges if None not in (a, b) and a != b for v in (a, b)}
    got = {r["node"]: r["component"] for r in connected_components(spark.createDataFrame(edges, "src long, dst long")).collect()}
    assert got == {v: root(v) for v in touched}
    assert connected_components(spark.createDataFrame([], "src long, dst long")).count() == 0


def test_join_hot_is_a_join(spark):
    rng = random.Random(2)
    rows = spark.createDataFrame([(rng.choice([1, 1, 1, 1, 2, 3, None, 9]), i) for i in range(9000)], "k long, i long")
    table = spark.createDataFrame([(1, 4500, "a"), (2, 1100, "b"), (3, 5, "c"), (4, 1, "d")], "k long, n long, x string").cache()
    for how in ("left", "inner"):
        want = collections.Counter(tuple(r) for r in rows.join(table, "k", how).select("k", "i", "x").collect())
        assert collections.Counter(tuple(r) for r in join_hot(rows, table, "k", ["i"], how).select("k", "i", "x").collect()) == want
    assert join_hot(rows, table.limit(0), "k", ["i"]).count() == 9000


def test_ranges(spark):
    df = spark.createDataFrame([(i * i % 1009,) for i in range(3000)] + [(None,)], "k long")
    edges = range_edges(df, "k")
    got = df.select("k", range_of(F.col("k"), edges).alias("r")).collect()
    for r in got:
        assert r["r"] == (-1 if r["k"] is None else sum(e < r["k"] for e in edges))
    assert len({r["r"] for r in got}) > 10
    names = df.select(F.concat(F.lit("é"), F.col("k").cast("string")).alias("k"))
    edges = range_edges(names, "k")
    got = names.select("k", range_of(F.col("k"), edges).alias("r")).collect()
    for r in got:
        assert r["r"] == (-1 if r["k"] is None else sum(e < r["k"] for e in edges))
    assert len({r["r"] for r in got}) > 10 and range_edges(names.limit(0), "k") == []


@pytest.mark.parametrize(
    "value,want",
    [("500", "Numeric"), ("-1.5", "Numeric"), ("1,234,567.8", "Numeric"), ("TRUE", "Boolean"), ("no", "Boolean"), ("10.0.0.1", "IP"), ("999.1.1.1", "Other"), ("###", "Non-Alphanumeric"),
     ("{0A000000-0000-4000-8000-00000000000b}", "GUID"), ("https://x.example/a?b=1", "URI"), ("/a/b", "URI"), ("down for now", "Alphabetical"), ("été", "Alphabetical"), ("node 7", "Alphanumeric"), ("7b", "Alphanumeric"), ("a-b", "Other"), ("", "Other"), (None, "Other")],
)
def test_value_types(spark, value, want):
    assert spark.createDataFrame([(value,)], "v string").select(T.value_type(F.col("v"))).first()[0] == want


def test_key_value_lines(spark):
    lines = ["Name:value", "A: b: c", "at 10:30 it broke", "see https://x.example/y", "Empty:", ": alone", "Code 7: x", "- Größe: 5", "Link: https://x.example:80/y", "one two three four five six seven: x", None, ""]
    df = spark.createDataFrame([(1, i, x) for i, x in enumerate(lines)], "report_id long, sent_no int, text string")
    got = {r["sent_no"]: (r["name"], r["value"]) for r in patterns.key_value(df).collect()}
    assert got == {0: ("Name", "value"), 1: ("A", "b: c"), 6: ("Code 7", "x"), 7: ("- Größe", "5"), 8: ("Link", "https://x.example:80/y")}


def test_cleaning(spark):
    html = "<p>a&amp;b</p><table><tr><td>x</td><td>y</td></tr></table><table><tr><td>1</td><td>2</td><td>3</td></tr></table><script>no()</script>end"
    df = spark.createDataFrame([(1, html), (2, None), (3, "")], "report_id long, description string")
    got = [(r["report_id"], r["text"]) for r in T.sentences(df).orderBy("report_id", "sent_no").collect()]
    assert got == [(1, "a&b"), (1, "x\ty"), (1, "end")]
    tokens = spark.createDataFrame([("HTTPServer talkTo https://a.b/c 10.1.2.3 x=1",)], "s string").select(T.tokenize(F.col("s"))).first()[0]
    assert tokens == ["HTTP", "Server", "talk", "To", "https://a.b/c", "10.1.2.3", "x", "=", "1"]


def test_windows_keep_all_tokens(spark):
    df = spark.createDataFrame([(1, list("abcdefghij"))], "id long, tokens array<string>")
    got = [r["tokens"] for r in T.windows(df, max_len=4, stride=3).orderBy("window").collect()]
    assert got == [list("abcd"), list("defg"), list("ghij")]


def test_longest_value_wins(spark):
    s = spark.createDataFrame([(1, 0, "in New York City now"), (2, 0, "York: x")], "report_id long, sent_no int, text string")
    d = spark.createDataFrame([("New York", 2, "state", 1), ("New York City", 3, "city", 1), ("City", 1, "word", 1)], "value string, tokens int, entity string, support long")
    seeds = spark.createDataFrame([(2, 0, "York", "x")], "report_id long, sent_no int, entity string, value string")
    assert [(r["entity"], r["begin"], r["size"]) for r in propagate.propagate(s, d, seeds).collect()] == [("city", 1, 3)]


def test_propagation_reaches_prose(spark, small):
    got = {r["place"]: r["recall"] for r in mining.QUERIES["propagation_recall"][0](spark, small).collect()}
    assert got["kv"] > 0.95 and got["table"] > 0.95 and got["prose"] > 0.6
    m = mining.mined(spark, small)
    assert m.propagated.where("entity in ('needs callback', 'problem note', 'order status')").count() == 0


def test_published_precision_points(spark):
    hits = {35: 34, 50: 48, 75: 64, 100: 77}
    assert [round(v / k, 2) for k, v in hits.items()] == [0.97, 0.96, 0.85, 0.77]
    df = spark.createDataFrame([(i, i != 3) for i in range(1, 6)], "rank int, is_valid boolean")
    assert [(r["n"], r["hits"]) for r in metrics.precision_at(df, (1, 5, 10)).orderBy("n").collect()] == [(1, 1), (5, 4)]


def test_crf_by_enumeration():
    rng = np.random.default_rng(1)
    for n, k in ((1, 3), (4, 3), (5, 2)):
        e, t, s, x = rng.normal(size=(2, n, k)), rng.normal(size=(k, k)), rng.normal(size=k), rng.normal(size=k)
        paths = np.array(list(itertools.product(range(k), repeat=n)))
        for b in range(2):
            scores = crf.path_score(np.repeat(e[b : b + 1], len(paths), 0), paths, t, s, x)
            assert crf.log_partition(e, t, s, x)[b] == pytest.approx(math.log(np.exp(scores).sum()))
            assert (crf.viterbi(e, t, s, x)[b] == paths[scores.argmax()]).all()


@pytest.mark.parametrize("attention,tasks", [(False, 1), (True, 1), (True, 2)])
def test_tagger_gradients(attention, tasks):
    rng = np.random.default_rng(2)
    m = model.Tagger(3, 2, (("O", "A", "B"), ("O", "X"))[:tasks], attention, (1.0, 0.5)[:tasks])
    x = rng.normal(size=(2, 4, 3))
    ys = [rng.integers(0, len(t), (2, 4)) for t in m.tags]
    _, grads = m.loss_grad(x, ys)
    for name, g in grads.items():
        flat = m.weights[name].reshape(-1)
        for i in rng.choice(len(flat), min(4, len(flat)), replace=False):
            kept = flat[i]
            flat[i] = kept + 1e-5
            up, _ = m.loss_grad(x, ys)
            flat[i] = kept - 1e-5
            down, _ = m.loss_grad(x, ys)
            flat[i] = kept
            assert g.reshape(-1)[i] == pytest.approx((up - down) / 2e-5, rel=1e-4, abs=1e-7), name


def test_pooled_attention_gradient():
    rng = np.random.default_rng(5)
    h, u, d_r = rng.normal(size=(2, 4, 3)), rng.normal(size=3), rng.normal(size=(2, 3))
    value = lambda h, u: float((model.attention(h, u, "pooled")[0] * d_r).sum())
    r, a = model.attention(h, u, "pooled")
    d_h, d_u = model.attention_back(h, u, a, r, d_r, "pooled")
    for x, g in ((h, d_h), (u, d_u)):
        for i in range(x.size):
            kept = x.reshape(-1)[i]
            x.reshape(-1)[i] = kept + 1e-6
            up = value(h, u)
            x.reshape(-1)[i] = kept - 1e-6
            down = value(h, u)
            x.reshape(-1)[i] = kept
            assert g.reshape(-1)[i] == pytest.approx((up - down) / 2e-6, rel=1e-4, abs=1e-8)


TYPES = "entity string, value_type string"


def test_tags_of_tokens(spark):
    s = spark.createDataFrame([(1, 0, "Source Ip: 10.0.0.1, orderPriority=1-URGENT"), (1, 1, "...")], "report_id long, sent_no int, text string")
    m = spark.createDataFrame([(1, 0, 2, 1, "ip", "10.0.0.1"), (1, 0, 3, 1, "priority", "x")], "report_id long, sent_no int, begin int, size int, entity string, value string")
    t = spark.createDataFrame([("ip", "IP"), ("priority", "Other")], TYPES)
    r = labeling.encode(s, m, t).where("sent_no = 0").first()
    assert r["tokens"] == ["Source", "Ip", ":", "10.0.0.1", ",", "order", "Priority", "=", "1", "-", "URGENT"]
    assert r["entity_tags"] == ["O", "O", "O", "B-ip", "I-ip", "B-priority", *["I-priority"] * 5] and r["type_tags"][3] == "B-IP"
    assert r["starts"] == [True, True, False, True, False, True, *[False] * 5]
    rows = labeling.encode(s, m, t)
    assert [(x["begin"], x["size"], x["entity"], x["value"]) for x in train.mentions_of(rows, "entity_tags").orderBy("begin").collect()] == [(3, 2, "ip", "10.0.0.1,"), (5, 6, "priority", "orderPriority=1-URGENT")]
    assert [x["tokens"] for x in labeling.encode(s, m, t, tokens="no separators").orderBy("sent_no").collect()] == [["Source", "Ip", "10.0.0.1", "order", "Priority", "1", "URGENT"], ["..."]]
    assert labeling.encode(s, m, t, tokens="blanks").where("sent_no = 0").first()["tokens"] == s.first()["text"].split(" ")


def tiny_tagger():
    return model.joint_tagger(8, 6, ("O", "B-ip", "I-ip"), ("O", "B-IP", "I-IP"))


def test_long_sentences_are_learned_and_tagged(spark):
    n = 700
    tokens, tags = [f"w{i % 5}" for i in range(n)], ["B-ip" if i % 5 == 0 else "O" for i in range(n)]
    rows = spark.createDataFrame([(1, 0, tokens, tags, [x.replace("ip", "IP") for x in tags]), (2, 0, ["a"], ["O"], ["O"]), (3, 0, [], [], [])], "report_id long, sent_no int, tokens array<string>, entity_tags array<string>, type_tags array<string>")
    got = train.in_windows(rows).where("report_id = 1").orderBy("window").collect()
    assert [len(r["tokens"]) for r in got] == [300, 300, 200] and all(r["entity_tags"] == tags[250 * r["window"] :][:300] for r in got)
    m, losses = train.fit(rows, tiny_tagger(), rounds=2, shards=2)
    assert len(losses) == 2 and losses[1] < losses[0]
    out = {r["report_id"]: r for r in train.tag(rows, m).collect()}
    assert len(out[1]["pred"]) == n and len(out[2]["pred"]) == 1 and out[3]["pred"] == []
    shares = train.attention_shares(rows, m).where("report_id = 1").first()["shares"]
    assert len(shares) == n and sum(shares) == pytest.approx(1)


def test_vector_files(tmp_path):
    (tmp_path / "v.txt").write_text("2 3\nap 1 2 3\nbee 4 5 6.5\nodd 1 2\n")
    table = vectors.load_vectors(str(tmp_path / "v.txt"), 3)
    assert set(table) == {"ap", "bee"} and table["bee"].tolist() == [4, 5, 6.5]
    got = train.token_matrix(["Ap", "zz9"], 3, table)
    assert got[0].tolist() == [1, 2, 3] and np.array_equal(got[1], vectors.word_vector("zz0", 3))


def test_serving_by_a_tagger_on_tables_and_streams(spark, small):
    from reportgraph.operators import service
    from reportgraph.sources import corpus
    from reportgraph.streaming import streams

    m = tiny_tagger()
    reports = corpus.event_reports(spark, small)
    want = service.auto(reports.withColumn("description", F.split("description", "\nBatch")[0]), ("error",), m)
    got = streams.auto_trigger(spark, small, ("error",), m)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    one = service.by_id(reports, None, 7, m)
    assert one.columns == ["report_id", "entities"] and one.count() <= 1


def test_life_cycles_over_batches(spark, small, tmp_path):
    """Files that come one after another in time give the same as all at once."""
    from reportgraph.streaming import streams

    events = spark.read.parquet(f"{small}/events.parquet").toPandas().sort_values(["ts", "event_id"])
    step = -(-len(events) // 4)
    for k in range(4):
        events.iloc[k * step : (k + 1) * step].to_parquet(tmp_path / f"{k}.parquet", coerce_timestamps="us")
        os.utime(tmp_path / f"{k}.parquet", (1_000_000 + k, 1_000_000 + k))
    users = {u: sum(1 for _ in g) for u, g in itertools.groupby(sorted(events["user_id"]))}
    want = {}
    for u, t in zip(events["user_id"], events["event_type"]):
        is_open, closed = want.get(u, (False, 0))
        want[u] = (True, closed) if t == "error" else (False, closed + 1) if t == "login" and is_open else (is_open, closed)
    got = {r["user_id"]: (r["is_open"], r["closed"]) for r in streams.life_cycle(spark, small, str(tmp_path), 1).collect()}
    assert got == want and len(got) == len(users)
    assert {r["user_id"]: (r["is_open"], r["closed"]) for r in streams.life_cycle_processor(spark, small, str(tmp_path), 1).collect()} == want
    late = streams.late_rows(spark, small, str(tmp_path), 1).collect()
    assert sum(r["n"] for r in late) == len(events) and not any(r["late"] for r in late)
    os.utime(tmp_path / "0.parquet", (2_000_000, 2_000_000))  # the first hours come last
    late = streams.late_rows(spark, small, str(tmp_path), 1).collect()
    assert sum(r["n"] for r in late if r["late"]) == step


def test_nearest_by_brute_force(spark):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(300, 5))
    x[7] = x[3]
    pts = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vector array<double>")
    got = {(r["id"], r["rank"]): (r["other"], r["distance"]) for r in titles.nearest(pts, 4, block=64).collect()}
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(-1))
    np.fill_diagonal(d, np.inf)
    for i in range(300):
        for r, j in enumerate(np.lexsort((np.arange(300), d[i]))[:4], 1):
            assert got[i, r] == (j, pytest.approx(d[i, j]))
    assert len(got) == 1200 and titles.nearest(pts.limit(0), 3).count() == 0 and titles.nearest(pts.limit(1), 3).count() == 0


def test_kernel_features_approach_the_kernel(spark):
    from pyspark.ml.functions import array_to_vector, vector_to_array

    rng = np.random.default_rng(6)
    x = rng.normal(size=(40, 6))
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "i long, x array<double>").withColumn("features", array_to_vector("x"))
    z = np.array([r[0] for r in triage.fourier(rows, n=4000, gamma=0.05).orderBy("i").select(vector_to_array("features")).collect()])
    exact = np.exp(-0.05 * ((x[:, None] - x[None]) ** 2).sum(-1))
    assert np.abs(z @ z.T - exact).max() < 0.12


def test_a_cluster_must_name_its_shared_folder():
    from types import SimpleNamespace

    from reportgraph.sources import io

    none = SimpleNamespace(getCheckpointDir=lambda: SimpleNamespace(isEmpty=lambda: True))
    session = SimpleNamespace(sparkContext=SimpleNamespace(master="spark://host:7077", _jsc=SimpleNamespace(sc=lambda: none)), conf=SimpleNamespace(get=lambda k, d: d))
    with pytest.raises(ValueError):
        io.shared_dir(session)


def test_graph_match(spark):
    e = spark.createDataFrame([("r1", "v1", "m"), ("r2", "v1", "m"), ("r2", "v2", "m"), ("r3", "v2", "m"), ("v1", "t", "is"), ("v2", "t", "is"), ("r1", "r9", "x")], "src string, dst string, kind string")
    two = graph.match(e, [("a", "m", "v"), ("b", "m", "v")])
    assert {tuple(r) for r in two.select("a", "b", "v").collect()} == {("r1", "r2", "v1"), ("r2", "r1", "v1"), ("r2", "r3", "v2"), ("r3", "r2", "v2")}
    assert graph.match(e, [("a", "m", "v"), ("v", "is", "t")]).count() == 4
    with pytest.raises(ValueError):
        graph.match(e, [("a", "m", "v"), ("c", "is", "t")])


def test_hashed_neighbours_are_neighbours(spark):
    rng = np.random.default_rng(8)
    x = np.repeat(rng.normal(size=(60, 8)) * 4, 3, axis=0) + rng.normal(size=(180, 8)) * 0.05
    pts = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vector array<double>")
    exact = {(r["a"], r["b"]) for r in titles.neighbour_pairs(pts, 1.0).collect()}
    found = {(r["a"], r["b"]) for r in titles.neighbour_pairs_hashed(pts, 1.0).collect()}
    assert found <= exact and len(found) >= 0.9 * len(exact) > 100
    assert {tuple(r) for r in titles.dbscan(pts, 1.0, 3, method="hashed").collect()} == {tuple(r) for r in titles.dbscan(pts, 1.0, 3).collect()}


def test_importances_by_source(spark):
    rng = random.Random(3)
    rows = [(i, f"t{i % 3}", rng.choice(["red", "blue"]), "", [f"zone={i % 3}", f"noise={rng.randrange(4)}"]) for i in range(240)]
    f = triage.features(spark.createDataFrame(rows, "report_id long, team string, words string, described string, entries array<string>"), dim=4)
    got = {r["feature"]: r for r in triage.importances(f).collect()}
    assert got["zone"]["rank"] == 1 and got["zone"]["inputs"] == 3 and sum(r["importance"] for r in got.values()) == pytest.approx(1)
    assert {"title", "descriptive values", "noise"} <= set(got)
    for m in ("knn", "knn_hashed"):
        r = triage.cross_validate(f, m, folds=3).agg(F.sum("correct").alias("c"), F.sum("rows").alias("n")).first()
        assert r["n"] == 240 and r["c"] > 200, m


def test_attention_shares():
    h, u = np.random.default_rng(3).normal(size=(2, 5, 4)), np.ones(4)
    pooled, a = model.attention(h, u, "pooled")
    assert np.allclose(a.sum(1), 1) and np.allclose(pooled, np.tanh(np.einsum("bn,bnh->bh", a, h)))


def test_dbscan_rings(spark):
    pts = [(i, [r * math.cos(a), r * math.sin(a)]) for i, (r, a) in enumerate([(1.0, 2 * math.pi * k / 20) for k in range(20)] + [(4.0, 2 * math.pi * k / 80) for k in range(80)])]
    pts += [(200, [10.0, 10.0])]
    got = {r["id"]: r["cluster_id"] for r in titles.dbscan(spark.createDataFrame(pts, "id long, vector array<double>"), 0.4, 3).collect()}
    assert {got[i] for i in range(20)} == {0} and {got[i] for i in range(20, 100)} == {20} and got[200] == -1


def test_top_k_ties(spark):
    c = spark.createDataFrame([(1, 0, n, "v", "key_value") for n in ("The Zone", "zone", "portName", "port 7")], "report_id long, sent_no int, name string, value string, pattern string")
    got = [(r["gram"], r["freq"]) for r in labeling.top_k_types(c, 10).orderBy("rank").collect()]
    assert got == [("zone", 2), ("port name", 1)]
    names = {r["name"]: r["entity"] for r in labeling.resolve_names(c, labeling.top_k_types(c, 10)).collect()}
    assert names == {"the zone": "zone", "zone": "zone", "port name": "port name"}


def test_plans_stay_native(spark, small):
    from reportgraph.sources import corpus

    plan = patterns.extract_all(T.sentences(corpus.order_reports(spark, small)))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "CartesianProduct" not in plan


def test_kept_options_with_and_without_their_defaults(spark, small):
    from reportgraph.plans import applications

    runs = []

    @applications.kept
    def numbered_for_test(spark, sf_dir, kind="a", size=1):
        runs.append((kind, size))
        return len(runs)

    assert numbered_for_test(spark, small) == numbered_for_test(spark, small, "a") == numbered_for_test(spark, small, "a", 1) == 1
    assert numbered_for_test(spark, small, "b") == 2 and len(runs) == 2


def test_sentences_of_one_form_are_decoded_once(spark, monkeypatch):
    table = [(i, 0, ["Ip", f"10.0.0.{i % 10}", "Down" if i % 2 else "down"]) for i in range(300)]
    rows = spark.createDataFrame(table, "report_id long, sent_no int, tokens array<string>")
    seen = spark.sparkContext.accumulator(0)
    decoded = train._decoded

    def counted(forms, *more):
        seen.add(forms.count())
        return decoded(forms, *more)

    monkeypatch.setattr(train, "_decoded", counted)
    vectors = {"ip": np.ones(8), "10.0.0.1": np.full(8, 2.0)}
    for m in (tiny_tagger(), model.joint_tagger(8, 6, ("O", "B-ip", "I-ip"), ("O", "B-IP", "I-IP"), vectors=vectors)):
        start = seen.value
        got = {r["report_id"]: r for r in train.tag(rows, m).collect()}
        assert len(got) == 300 and seen.value - start <= 4
        for i in (0, 1, 2, 7):
            x = train.token_matrix(list(train.spelled(table[i][2], m.vectors)), m.dim, m.vectors)[None]
            assert got[i]["tokens"] == table[i][2] and got[i]["pred"] == [m.tags[0][k] for k in m.decode(x)[0]]
    monkeypatch.setattr(train, "BROADCAST_FORMS", 0)
    assert {r["report_id"]: r for r in train.tag(rows, m).collect()} == got


def test_nearest_of_all_training_rows(spark, monkeypatch):
    from pyspark.ml.functions import array_to_vector

    monkeypatch.setattr(triage, "PACK", 37)
    rng = np.random.default_rng(5)
    x = np.concatenate([np.round(rng.normal(size=(300, 3)) * 2), np.full((300, 1), 9.0)], 1)
    y = rng.integers(0, 3, 300).astype(float)
    rows = spark.createDataFrame([(i, float(y[i]), v.tolist()) for i, v in enumerate(x)], "report_id long, label double, x array<double>").withColumn("features", array_to_vector("x"))
    learn, ask = rows.where("report_id % 3 <> 0"), rows.where("report_id % 3 = 0")
    got = {r["report_id"]: r["prediction"] for r in triage.KNearest().fit(learn).transform(ask).collect()}
    ids = np.array([i for i in range(300) if i % 3])
    for i in range(0, 300, 3):
        near = ids[np.lexsort((ids, ((x[ids] - x[i]) ** 2).sum(1)))[:5]]
        votes = [(-(y[near] == c).sum(), c) for c in (0.0, 1.0, 2.0)]
        assert got[i] == min(votes)[1]
    hashed = triage.HashedNearest(width=1.0, tables=2).fit(learn)
    pairs = hashed.model.approxSimilarityJoin(ask.select("report_id", "features"), learn.select("report_id", "features"), float("inf"), "d")
    met = {}
    for r in pairs.select("datasetA.report_id", "datasetB.report_id").toDF("a", "b").collect():
        met.setdefault(r["a"], set()).add(r["b"])
    found = {}
    for r in hashed.neighbours(hashed._hashed(ask)).collect():
        found.setdefault(r["report_id"], {})[r["rank"]] = r["other"]
    for i in range(0, 300, 3):
        own = np.array(sorted(met.get(i, ())), int)
        near = own[np.lexsort((own, ((x[own] - x[i]) ** 2).sum(1)))[:5]].tolist()
        assert [found.get(i, {})[k] for k in sorted(found.get(i, {}))] == near


def test_classes_are_fitted_with_own_properties(spark):
    from pyspark.ml.classification import LinearSVC, OneVsRest
    from pyspark.ml.functions import array_to_vector

    rng = np.random.default_rng(6)
    x = rng.normal(size=(400, 2))
    y = (x[:, 0] > 0).astype(int) + 2 * (x[:, 1] > 0)
    rows = spark.createDataFrame([(i, float(y[i]), v.tolist()) for i, v in enumerate(x)], "report_id long, label double, x array<double>").withColumn("features", array_to_vector("x")).persist()
    svm = LinearSVC(maxIter=12, regParam=0.001)
    owners = []

    class Probe:
        labelCol = svm.labelCol

        def copy(self, extra):
            return self

        def fit(self, binary):
            owners.append(spark._jvm.System.identityHashCode(spark.sparkContext._jsc.sc().getLocalProperties()))
            return svm.copy({svm.labelCol: "own"}).fit(binary)

    triage.one_against_rest(rows, Probe())
    assert len(owners) == len(set(owners)) == 4
    got = triage.one_against_rest(rows, svm)
    same = OneVsRest(classifier=svm, parallelism=1).fit(rows)
    assert all(np.allclose(a.coefficients.toArray(), b.coefficients.toArray()) for a, b in zip(got.models, same.models)) and len(got.models) == 4
    assert [r["prediction"] for r in got.transform(rows).orderBy("report_id").collect()] == [r["prediction"] for r in same.transform(rows).orderBy("report_id").collect()]


def test_hashed_pairs_of_a_crowded_bucket(spark):
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    rng = np.random.default_rng(9)
    x = rng.normal(size=(400, 4)) * 0.6
    pts = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vector array<double>")
    rows = pts.select("id", array_to_vector("vector").alias("features"))
    lsh = BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=1.0, numHashTables=6, seed=7).fit(rows)
    pairs = lsh.approxSimilarityJoin(rows, rows, 0.5, "d").select(F.col("datasetA.id").alias("a"), F.col("datasetB.id").alias("b")).where("a < b")
    got = titles.neighbour_pairs_hashed(pts, 0.5, block=64)
    assert sorted((r["a"], r["b"]) for r in got.collect()) == sorted(tuple(r) for r in pairs.collect())
    assert "MapInPandas" in got._jdf.queryExecution().toString()


def test_nearest_shuffles_no_point_twice(spark):
    rng = np.random.default_rng(10)
    x = np.round(rng.normal(size=(500, 2)), 1)
    pts = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vector array<double>")
    got = titles.nearest(pts, 3, block=60)
    found = {(r["id"], r["rank"]): r["other"] for r in got.collect()}
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(-1))
    np.fill_diagonal(d, np.inf)
    ids = np.arange(500)
    assert all(found[i, r + 1] == ids[np.lexsort((ids, d[i]))][r] for i in range(500) for r in range(3))
    assert "applyInPandas" not in str(got._jdf.queryExecution().optimizedPlan()) and "FlatMapGroupsInPandas" not in str(got._jdf.queryExecution().optimizedPlan())


def test_word_vectors_are_learned_in_many_tasks(spark):
    rows = spark.createDataFrame([(["a", "b", "c", f"w{i % 7}"],) for i in range(200)], "tokens array<string>")
    got = vectors.train_word2vec(rows, dim=4, min_count=3)
    assert got.getNumPartitions() == spark.sparkContext.defaultParallelism > 1 and got.getVectors().count() == 10


def test_kinds_of_entities_keep_no_values_in_buffers(spark):
    rows = [("note", f"a b c d e {i}") for i in range(6)] + [("note", "x")] * 6 + [("code", "1")] * 5 + [("code", "1 2")] * 3
    m = spark.createDataFrame(rows, "entity string, value string")
    kinds = triage.entity_kind(m, spark.createDataFrame([("note", "Alphabetical"), ("code", "Other")], "entity string, value_type string"))
    assert {tuple(r) for r in kinds.collect()} == {("note", 1, 0.583333, "descriptive"), ("code", 1, 0.25, "categorical")}
    assert "percentile" not in kinds._jdf.queryExecution().optimizedPlan().toString()


def test_differences_come_from_orders(spark, small):
    from reportgraph.plans.registry import QUERIES

    plan = QUERIES["delta_pct"][0](spark, small)
    assert any("orders.parquet" in f for f in plan.inputFiles()) and plan.count() == 5


def test_reports_are_dealt_to_all_tasks(spark, small):
    """The table of orders is one small file, whose reports one task would make."""
    from reportgraph.sources import corpus

    assert corpus.order_reports(spark, small).rdd.getNumPartitions() >= 4


def test_sentences_to_learn_from_are_told_before_they_are_cut(spark):
    long = " ".join(["w"] * 400)
    s = spark.createDataFrame([(i, i % 3, long if i in (5, 77) else f"Source Ip: 10.0.0.{i}") for i in range(120)], "report_id long, sent_no int, text string")
    none = spark.createDataFrame([], "report_id long, sent_no int, begin int, size int, entity string, value string")
    types = spark.createDataFrame([("ip", "IP")], TYPES)
    some = train.fit_sentences(s, 20)
    assert 20 <= some.count() <= 22 and {5, 77} <= {r["report_id"] for r in some.collect()}
    whole, part = (train.fit(labeling.encode(x, none, types), tiny_tagger(), rounds=1, max_sentences=20)[0].weights for x in (s, some))
    assert all(np.allclose(whole[k], part[k]) for k in whole)


def test_values_from_texts_are_those_from_tokens(spark, monkeypatch):
    """Texts that differ in digits are cut and decoded once, and values are the same as from each sentence's own tokens."""
    texts = [f"Source Ip: 10.0.{i}.7, orderPriority=1-URGENT\tA{i}b  Ärger😀{i} x@y{i}.org" for i in range(40)] + ["...", "", "http://a.b/1 tab\tt 12", "\u0663 7\x0b8 \x0c 9", "HTTPServer v2 😀 00", "null 5 😀😀 6-7"]
    s = spark.createDataFrame([(i, 0, t) for i, t in enumerate(texts)] + [(99, 0, None)], "report_id long, sent_no int, text string")
    for seed in (2,):
        m = model.joint_tagger(8, 6, ("O", "B-ip", "I-ip", "B-x", "I-x"), ("O", "B-IP", "I-IP"), seed=seed)
        for tokens in ("words", "no separators", "blanks"):
            want = train.mentions_of(train.tag(labeling.token_rows(s.where("text IS NOT NULL"), tokens), m).drop("spans"))
            assert sorted(map(tuple, train.text_mentions(s, m, tokens).collect())) == sorted(map(tuple, want.collect()))
    cut, seen = train.token_rows, spark.sparkContext.accumulator(0)

    def counted(rows, *more):
        seen.add(rows.count())
        return cut(rows, *more)

    monkeypatch.setattr(train, "token_rows", counted)
    assert train.text_mentions(s, m).select("report_id").distinct().count() > 40 and seen.value <= 10


def test_the_edge_in_time_is_exact_and_no_sketch(spark, monkeypatch):
    monkeypatch.setattr(labeling.F, "percentile_approx", None)
    for days in ([3] * 7 + [1] * 2 + [9, 4, None], [5], [2, 1], list(range(1, 29)) * 40):
        rows = spark.createDataFrame([(i, d and f"2020-01-{d:02d}") for i, d in enumerate(days)], "report_id long, day string").withColumn("at", labeling.F.to_timestamp("day"))
        known = sorted(d for d in days if d)
        edge = known[max(1, math.ceil(0.8 * len(known))) - 1]
        got = {r["report_id"]: r["part"] for r in labeling.temporal_split(rows, "at").collect()}
        assert got == {i: "test" if d and d > edge else "train" for i, d in enumerate(days)}
    assert {r["part"] for r in labeling.temporal_split(rows.where("at IS NULL"), "at").collect()} <= {"train"}


@pytest.mark.parametrize("few", [True, False])
def test_windows_by_brute_force(spark, monkeypatch, few):
    """Each word is a window by itself, so sentences are not gathered again by a shuffle to cut out longer ones."""
    if not few:
        monkeypatch.setattr(propagate, "BROADCAST_VALUES", 0)
    values = [("new york", 2, "city"), ("york", 1, "town"), ("new york city hall", 4, "place"), ("rome.", 1, "x"), ("10.0.0.1", 1, "ip"), ("...", 1, "dots")]
    texts = ["we saw new york, york. new\tyork city hall!", "rome. rome new york", "at 10.0.0.1!? new", "... new york city", ""]
    s = spark.createDataFrame([(1, i, t) for i, t in enumerate(texts)], "report_id long, sent_no int, text string")
    d = spark.createDataFrame([(v, n, e, 1) for v, n, e in values], "value string, tokens int, entity string, support long")
    found = propagate.occurrences(s, d)
    want = set()
    for i, t in enumerate(texts):
        w = re.split("[ \t]+", t)
        want |= {(i, b, n, x) for b in range(len(w)) for n in range(1, 5) if b + n <= len(w) and (x := re.sub("[,.;!?]+$", "", " ".join(w[b : b + n]))) in dict((v, e) for v, _, e in values)}
    got = [(r["sent_no"], r["begin"], r["size"], r["value"]) for r in found.join(d.select("value"), "value").collect()]
    assert set(got) == want and len(got) == len(want)
    assert ("hashpartitioning(report_id" in found._jdf.queryExecution().executedPlan().toString()) != few


def test_sentences_to_learn_from_of_some_reports(spark):
    long = " ".join(["w"] * 400)
    s = spark.createDataFrame([(i, k, long if i in (5, 77) else f"Source Ip: 10.0.0.{i}") for i in range(120) for k in range(2)], "report_id long, sent_no int, text string")
    for share in (2, 60):  # of the first sentences there are enough, or too few, of those reports
        reports = spark.createDataFrame([(i, "train") for i in range(120) if i % share == 1 or i in (5, 78)], "report_id long, part string")
        want = train.fit_sentences(s.join(reports, "report_id"), 20)
        got = train.fit_sentences(s, 20, reports)
        key = lambda df: sorted((r["report_id"], r["sent_no"], r["part"], r["text"]) for r in df.collect())
        assert key(got) == key(want)


def test_few_forms_are_decoded_by_few_tasks(spark, monkeypatch):
    """A task decodes sentences of one length together; two hundred tasks for some thousand forms would take a few at a time."""
    forms = spark.range(5000).selectExpr("array(cast(id as string)) AS form", "1L AS n")
    before = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        spark.conf.set("spark.sql.shuffle.partitions", "50")
        assert train._dealt(forms).rdd.getNumPartitions() == 4
        monkeypatch.setattr(train, "TASK_FORMS", 100)
        dealt = train._dealt(forms)
        assert dealt.rdd.getNumPartitions() == 50 and dealt.count() == 5000
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


def test_machines_of_all_folds_side_by_side(spark):
    """Machines fitted in common passes come as low as the library in as many steps, and the passes do not grow with classes and folds."""
    from pyspark.ml.classification import LinearSVC
    from pyspark.ml.functions import array_to_vector

    from reportgraph.operators import triage

    rng = np.random.default_rng(5)
    centres = rng.normal(0, 1, (6, 8)) * [1, 2, 0.1, 5, 1, 1, 1, 0]
    y = np.arange(600) % 6
    x = centres[y] + rng.normal(0, 0.8, (600, 8)) * [1, 1, 0.05, 3, 1, 1, 1, 0] + 3
    rows = spark.createDataFrame([(i, float(k), v.tolist()) for i, (k, v) in enumerate(zip(y, x))], "report_id long, label double, x array<double>")
    rows = rows.select("report_id", "label", array_to_vector("x").alias("features")).persist()
    folded = rows.withColumn("fold", F.pmod(F.xxhash64("report_id"), F.lit(3)).cast("int"))
    got = triage.MarginsOfFolds(folded, 3, steps=12, penalty=0.01)
    assert set(got.weights) == {(k, c) for k in range(3) for c in range(6)}
    binary = folded.where("fold <> 1").withColumn("own", (F.col("label") == 4).cast("double"))
    same = LinearSVC(maxIter=12, regParam=0.01, labelCol="own").fit(binary)
    part = binary.toPandas()
    m, sign = np.stack([v.toArray() for v in part["features"]]), np.where(part["own"] > 0, 1, -1)

    def loss(w, b):
        return np.maximum(0, 1 - sign * (m @ w + b)).mean() + 0.005 * ((w * m.std(0, ddof=1)) ** 2).sum()

    ours, theirs = loss(got.weights[1, 4][:-1], got.weights[1, 4][-1]), loss(same.coefficients.toArray(), same.intercept)
    assert got.weights[1, 4][7] == 0 and ours <= theirs * 1.02, (ours, theirs)

    spark.sparkContext.setJobGroup("machines", "machines")
    out = triage.cross_validate(rows, "linear_svm", folds=3).collect()
    jobs = len(spark.sparkContext.statusTracker().getJobIdsForGroup("machines"))
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert sum(r["rows"] for r in out) == 600 and sum(r["correct"] for r in out) > 300 and [r["fold"] for r in out] == [0, 1, 2]
    assert jobs < 120, jobs


def test_equal_sentences_are_learned_as_one_with_their_number(spark):
    """Each sentence counts once in the batches of an epoch, and a row of ``n`` sentences is the same as ``n`` rows."""
    import pandas as pd

    rng = np.random.default_rng(8)
    for top, few in ((1, 5), (900, 5), (900, 1000)):
        pdf = pd.DataFrame({"tokens": [["x"] * k for k in rng.integers(1, 4, 300)], "n": rng.integers(1, top + 1, 300)})
        got = [(part, n) for part, n in train.weighted_batches(pdf, few)]
        counted = pd.concat([pd.Series(n, index=part.index) for part, n in got]).groupby(level=0).sum()
        assert np.allclose(counted.sort_index(), pdf["n"]) and all((n > 0).all() and part["tokens"].map(len).nunique() == 1 for part, n in got)
    m = tiny_tagger()
    x, ys = rng.normal(size=(3, 4, 8)), [rng.integers(0, 3, (3, 4)) for _ in range(2)]
    often = np.repeat(np.arange(3), [1, 4, 2])
    one, all_ = m.loss_grad(x, ys, np.array([1, 4, 2])), m.loss_grad(x[often], [y[often] for y in ys])
    assert one[0] == pytest.approx(all_[0]) and all(np.allclose(one[1][k], all_[1][k]) for k in m.weights)
    kinds = [(["Ip", f"1{i}"] + ["x"] * (i % 3), ["O", "B-ip"] + ["O"] * (i % 3), ["O", "B-IP"] + ["O"] * (i % 3)) for i in range(9)]
    schema = "report_id long, sent_no int, tokens array<string>, entity_tags array<string>, type_tags array<string>"
    rows = spark.createDataFrame([(i, 0, *kinds[i % 9]) for i in range(5000)], schema)
    few = spark.createDataFrame([(i, 0, *kinds[i], sum(j % 3 == i for j in (k % 9 for k in range(5000)))) for i in range(3)], schema + ", n long")
    a, b = (train.fit(r, tiny_tagger(), rounds=1) for r in (rows, few))
    assert train.examples(rows, m).agg(F.count("*"), F.sum("n")).first() == (3, 5000) and a[1] == b[1]
    assert all(np.allclose(a[0].weights[k], b[0].weights[k]) for k in m.weights)


def test_weights_of_many_shards_are_added_in_tasks(spark, monkeypatch):
    rows = spark.createDataFrame([(k, f"w{j}", [2], 1.0 + k, 0.5, np.array([k, j], "<f8").tobytes()) for k in range(150) for j in range(2)], "part long, name string, shape array<int>, n double, loss double, flat binary")
    got = train._added(rows, 150)
    assert len(got) <= 2 * train.ADDED and sum(r["n"] for r in got) == 2 * sum(range(1, 151))
    assert sum(np.frombuffer(r["flat"], "<f8") for r in got if r["name"] == "w1").tolist() == [sum(range(150)), 150]


def test_dbscan_by_brute_force_without_pairs(spark, monkeypatch):
    """Crowded, chained, lonely and border points in blocks of a few; no pairs of points are listed."""
    monkeypatch.setattr(titles, "neighbour_pairs", None)
    rng = np.random.default_rng(12)
    x = np.concatenate([rng.normal(0, 0.05, (60, 2)), np.stack([np.arange(1, 6, 0.25), np.zeros(20)], 1), rng.uniform(-8, 8, (60, 2)), np.full((9, 2), 3.0)])
    w = rng.integers(1, 3, len(x))
    pts = spark.createDataFrame([(i * 3, v.tolist(), int(n)) for i, (v, n) in enumerate(zip(x, w))], "id long, vector array<double>, weight long")
    for crowd, eps, least in ((7, 0.25, 4), (7, 0.9, 5), (2048, 0.25, 4), (5, 1e-6, 4)):
        monkeypatch.setattr(titles, "CROWD", crowd)
        d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(-1))
        near = d <= eps
        core = near @ w >= least
        label = np.where(core, np.arange(len(x)), -1)
        for _ in range(len(x)):
            label = np.array([min(label[near[i] & core]) if core[i] else -1 for i in range(len(x))])
        for i in np.flatnonzero(~core & (near & core).any(1)):
            ok = np.flatnonzero(near[i] & core)
            label[i] = label[ok[np.lexsort((ok, d[i, ok]))[0]]]
        got = {r["id"] // 3: r["cluster_id"] for r in titles.dbscan(pts, eps, least, weight_col="weight").collect()}
        assert got == {i: 3 * c if c >= 0 else -1 for i, c in enumerate(label.tolist())} and len(set(label)) >= 2
    assert titles.dbscan(pts.limit(0), 0.5, 2).count() == 0 and [tuple(r) for r in titles.dbscan(pts.where("id = 6"), 0.5, 2).collect()] == [(6, -1)]


def test_word_vectors_keep_their_vocabulary_off_the_driver(spark, monkeypatch):
    """Words of like contexts are near, counts are those of the whole corpus, and no vocabulary or vector is collected."""
    rng = np.random.default_rng(4)
    table = [([f"{g}{rng.integers(5)}", f"{g}x", f"{g}{rng.integers(5)}", f"{g}y"],) for g in "ab" for _ in range(1500)] + [(["rare", "rare", None],), (["rare"],), (["Once"],), ([],), (None,)]
    rows = spark.createDataFrame(table, "tokens array<string>")
    monkeypatch.setattr(vectors, "PART_TOKENS", 2000)
    collect, sizes = type(rows).collect, []

    def counted(df):
        out = collect(df)
        sizes.append(len(out))
        return out

    monkeypatch.setattr(type(rows), "collect", counted)
    got = vectors.train_word2vec(rows, dim=8, iterations=10, min_count=3)
    assert got.getNumPartitions() == 7 and max(sizes) == 1
    monkeypatch.undo()
    v = {r["word"]: r["vector"].toArray() for r in got.getVectors().collect()}
    assert set(v) == {f"{g}{i}" for g in "ab" for i in (*range(5), "x", "y")} | {"rare"} and all(np.isfinite(x).all() and len(x) == 8 for x in v.values())
    cos = lambda a, b: v[a] @ v[b] / np.linalg.norm(v[a]) / np.linalg.norm(v[b])
    inside = [cos(f"{g}{i}", f"{g}{j}") for g in "ab" for i in range(5) for j in range(i)]
    assert min(inside) > max(cos(f"a{i}", f"b{j}") for i in range(5) for j in range(5))


def test_vector_files_hold_all_words(spark):
    import pickle

    from pyspark.ml.linalg import Vectors

    words = {f"Word{i}": np.random.default_rng(i).normal(size=6) for i in range(400)} | {"word7": np.ones(6)}
    rows = spark.createDataFrame([(w, Vectors.dense(v)) for w, v in words.items()], ["word", "vector"])
    t = vectors.vector_table(vectors.WordVectors(rows, 1))
    want = {f"word{i}": words[f"Word{i}"] for i in range(400)} | {"word7": words["word7"]}
    size = np.mean([np.sqrt((v**2).mean()) for v in want.values()])
    assert len(t) == 400 and all(w in t and np.allclose(t[w], v / size) for w, v in want.items()) and "Word1" not in t and "nothing" not in t
    assert len(pickle.dumps(t)) < 1000 and np.allclose(train.token_matrix(["WORD3"], 6, t)[0], t["word3"])
