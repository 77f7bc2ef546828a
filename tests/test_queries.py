"""Every query of the library with SQL, against that SQL."""

import pytest
from harness import compare

from reportgraph.plans.registry import QUERIES

WITH_SQL = sorted(k for k, (_, sql) in QUERIES.items() if sql)


@pytest.mark.parametrize("name", WITH_SQL)
def test_same_as_sql(spark, small, name):
    query, sql = QUERIES[name]
    compare(query(spark, small), sql, small)


def test_tagger_feeds_relations(spark, small):
    """A small tagger finds mentions in prose of later reports, and their pairs are those that the rendering puts on one line."""
    from pyspark.sql import functions as F

    from reportgraph.operators import relations
    from reportgraph.plans import applications
    from reportgraph.plans.mining import TRUE_PAIRS

    m = applications.model_mentions(spark, small, True)
    later = applications.sequences(spark, small).where("part = 'test'").select("report_id", "sent_no")
    assert m.join(later, ["report_id", "sent_no"]).where("entity = 'customer name'").count() > 50
    r = applications.model_relations(spark, small, True)
    top = {(x["e1"], x["e2"]) for x in r.orderBy(F.desc("f_joint")).limit(4).collect()}
    assert len(top & set(TRUE_PAIRS)) >= 3 and relations.keep(r).count() >= 3


def test_kept_results_follow_the_files(spark, tmp_path):
    import shutil

    from reportgraph.plans.mining import state_of

    for name in ("orders", "customer", "pages", "benchmark"):
        shutil.copy(f"/root/testdata/sf0.001/{name}.parquet", tmp_path)
    before = state_of(spark, str(tmp_path))
    assert state_of(spark, str(tmp_path)) == before
    shutil.copy("/root/testdata/sf0.01/orders.parquet", tmp_path)
    assert state_of(spark, str(tmp_path)) != before


def test_routing_is_judged_on_all_folds(spark, small, monkeypatch):
    from reportgraph.plans import applications

    sample = QUERIES["triage_sample"][0](spark, small).count()
    assert {r["rows"] for r in QUERIES["triage_naive_bayes"][0](spark, small).collect()} == {sample}
    monkeypatch.setattr(applications, "triage_accuracy", lambda spark, sf_dir, model, folds: (model, folds))
    assert all(QUERIES[f"triage_{m}"][0](spark, small) == (m, None) for m in applications.triage.MODELS)


def test_recall_reads_no_sentences_again(spark, small, monkeypatch):
    """Recall over the later reports, without another copy of all sentences; as counted by hand from the mentions that are given."""
    from reportgraph.plans import applications
    from reportgraph.plans.mining import mined
    from reportgraph.sources import corpus

    def never(*args):
        raise AssertionError("all sentences are joined and written")

    monkeypatch.setattr(applications, "split_sentences", never)
    monkeypatch.setattr(applications, "model_mentions", lambda spark, sf_dir: mined(spark, sf_dir).seeds)
    got = {r["place"]: (r["gold"], r["found"]) for r in QUERIES["model_recall"][0](spark, small).collect()}
    test = {r["report_id"] for r in applications.report_parts(spark, small).where("part = 'test'").collect()}
    found = {(r["report_id"], r["entity"], r["value"]) for r in mined(spark, small).seeds.collect()}
    want: dict[str, tuple[int, int]] = {}
    for r in corpus.order_reports_gold(spark, small).collect():
        if r["report_id"] in test:
            n, f = want.get(r["place"], (0, 0))
            want[r["place"]] = n + 1, f + ((r["report_id"], r["entity"], r["value"]) in found)
    assert got == want and len(want) == 3


def test_taggers_learn_from_all_earlier_sentences(spark, small, monkeypatch):
    from pyspark.sql import functions as F

    from reportgraph.plans import applications
    from reportgraph.plans.mining import mined

    given = []
    monkeypatch.setattr(applications.train, "fit", lambda rows, *more, **options: given.append((rows, options)))
    earlier = mined(spark, small).sentences.join(applications.report_parts(spark, small).where("part = 'train'"), "report_id", "left_semi")
    for tokens in ("words", "no separators", "blanks"):
        applications.fitted.__wrapped__(spark, small, "joint", tokens, 0.5, True)
        rows, options = given.pop()
        assert "max_sentences" not in options and rows.agg(F.sum("n")).first()[0] == earlier.count()
    rows = rows.withColumn("z", F.explode(F.arrays_zip("entity_tags"))).groupBy("z.entity_tags").agg(F.sum("n").alias("n"))
    want = applications.sequences(spark, small, "blanks", "train").select(F.explode("entity_tags").alias("t")).groupBy("t").count()
    assert sorted(map(tuple, rows.collect())) == sorted(map(tuple, want.collect()))


def test_attention_of_all_later_sentences(spark, small, monkeypatch):
    from pyspark.sql import functions as F

    from reportgraph.operators import labeling
    from reportgraph.plans import applications
    from reportgraph.tagger import model

    tagger = model.attention_tagger(4, 3, ("O", "B-x", "I-x"))
    monkeypatch.setattr(applications, "fitted", lambda *options: (tagger, []))
    got = QUERIES["attention_shares"][0](spark, small)
    later = labeling.token_rows(applications.split_sentences(spark, small).where("part = 'test'"))
    key = lambda df: sorted(map(tuple, df.groupBy("report_id", "sent_no").agg(F.array_join(F.array_sort(F.collect_list("token")), "|")).collect()))
    assert key(got) == key(later.select("report_id", "sent_no", F.explode("tokens").alias("token")))
    assert got.groupBy("report_id", "sent_no").agg(F.sum("share").alias("s")).where("abs(s - 1) > 1e-4").count() == 0
