from pyspark.sql import functions as F

from winnow.functions.textops import hash_uniform, n_tokens
from winnow.operators import lm, metrics_table, quantiles, similarity
from winnow.plans.settle import settle
from winnow.sources import replay
from winnow.sources.tables import SCHEMAS, read_table
from winnow.streaming import refresh


def stream(spark, sf):
    return refresh.arrivals(refresh.file_stream(spark, f"{sf}/documents.parquet", SCHEMAS["documents"]))


def test_soft_replay_equals_the_batch_draw(spark, sf):
    docs = read_table(spark, sf, "documents")
    cuts = refresh.frozen_grid(docs)
    got = {r.doc_id for r in refresh.drain(refresh.admit_soft(stream(spark, sf), cuts, 0.3).select("doc_id")).collect()}
    q = refresh.scored(docs).withColumn("q", quantiles.from_grid("entropy", cuts))
    want = {r.doc_id for r in q.where(hash_uniform("doc_id", 7) < 0.3 * F.col("q")).collect()}
    assert got == want and got


def test_hard_replay_equals_the_batch_filter(spark, sf):
    docs = read_table(spark, sf, "documents")
    got = {r.doc_id for r in refresh.drain(refresh.admit_hard(stream(spark, sf), 2.0).select("doc_id")).collect()}
    assert got == {r.doc_id for r in refresh.scored(docs).where("entropy >= 2.0").collect()}


def test_budget_per_period_equals_the_sequential_rule(spark, sf):
    """In order of arrival, each document that still fits, documents longer than an eighth of the budget among them."""
    for limit in (3_000, 20_000):
        got = {(str(r.period), r.doc_id) for r in refresh.drain(refresh.budgeted(stream(spark, sf), limit)).collect()}
        spent, want = {}, set()
        rows = refresh.arrivals(read_table(spark, sf, "documents")).select("doc_id", "arrival", n_tokens("text").alias("n"), F.date_trunc("day", "arrival").alias("period"))
        for r in rows.orderBy("arrival", "doc_id").collect():
            if spent.get(r.period, 0) + r.n <= limit:
                spent[r.period] = spent.get(r.period, 0) + r.n
                want.add((str(r.period), r.doc_id))
        assert got == want and len(want) < rows.count()


def test_frozen_scores_equal_the_batch_and_admit_alike(spark, sf):
    docs = read_table(spark, sf, "documents")
    model, centre = lm.train(read_table(spark, sf, "conversations")), similarity.centroid(read_table(spark, sf, "benchmark").withColumnRenamed("item_id", "seed_id"))
    table = metrics_table.score_all(docs, centre, model)
    frozen = refresh.freeze(model, centre, settle(table))
    want = {r.doc_id: r for r in table.collect()}
    for r in refresh.scored_by(docs, frozen).collect():
        w = want[r.doc_id]
        assert r.n_tokens == w.n_tokens and abs(r.similarity - w.similarity) < 1e-8 and (r.perplexity is None) == (w.perplexity is None)
        assert r.perplexity is None or abs(r.perplexity / w.perplexity - 1) < 1e-8
    batch = refresh.scored_by(docs, frozen)
    for selector, cut in (("task_similar", 0.05), ("novelty", 2000.0), ("blended", 0.6)):
        got = {r.doc_id for r in refresh.drain(refresh.admit(stream(spark, sf), frozen, selector, cut).select("doc_id")).collect()}
        assert got == {r.doc_id for r in batch.where(F.col(refresh.SCORES[selector]) >= cut).collect()} and 0 < len(got) < docs.count()
    drawn = {r.doc_id for r in refresh.drain(refresh.admit_drawn(stream(spark, sf), frozen, "blended", 0.4).select("doc_id")).collect()}
    assert drawn == {r.doc_id for r in batch.where(hash_uniform("doc_id", 7) < 0.4 * F.col("blended")).collect()} and drawn


def test_replay_source_in_batches_and_as_stream(spark, sf):
    replay.register(spark)
    opts = {"path": f"{sf}/documents.parquet", "batches": "4"}
    batch = spark.read.format("document_replay").options(**opts).load()
    n = read_table(spark, sf, "documents").count()
    assert batch.count() == n and batch.select("doc_id").distinct().count() == n


def test_late_rows_are_dropped(spark, tmp_path):
    """A first file moves the watermark; a second holds one row behind it and one ahead."""
    schema = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"

    def put(rows):
        spark.createDataFrame(rows, "event_id long, t string, user_id long, event_type string, value double, props string").select("event_id", F.to_timestamp("t").alias("ts"), "user_id", "event_type", "value", "props").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")

    def run():
        s = refresh.tumbling(spark.readStream.schema(schema).parquet(f"{tmp_path}/in"), "1 day", "1 hour")
        refresh.to_parquet(s, f"{tmp_path}/out", f"{tmp_path}/cp")
        return {(str(r.start)[:10], r.event_type): r.n for r in spark.read.parquet(f"{tmp_path}/out").collect()} if (tmp_path / "out").exists() else {}

    put([(1, "2024-01-01 10:00:00", 1, "view", 1.0, None), (2, "2024-01-05 10:00:00", 1, "view", 1.0, None)])
    run()
    put([(3, "2024-01-01 11:00:00", 1, "view", 1.0, None), (4, "2024-01-09 11:00:00", 1, "view", 1.0, None)])
    assert run() == {("2024-01-01", "view"): 1, ("2024-01-05", "view"): 1}
