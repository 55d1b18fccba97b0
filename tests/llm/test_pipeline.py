import re

import corpus_pipeline as cp
from winnow.llm import mixing, simhash, toxicity

ROWS = [
    (1, "a first line that is shared\nthe quick brown fox jumps over the lazy dog again and again", "en", "s1", 0),
    (2, "a first line that is shared\nsomething else entirely is written on this second line here", "en", "s2", 0),
    (3, "the quick brown fox jumps over the lazy dog again and again", "en", "s1", 0),
    (4, "you idiot scum moron", "en", "s2", 0),
    (5, None, None, None, None),
    (5, None, None, None, None),
]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def frame(spark, rows=ROWS):
    return spark.createDataFrame(rows, SCHEMA)


def test_stages_are_the_named_ones():
    assert [n for n, _ in cp.STAGES] == ["toxicity", "line_dedup", "simhash_near_dedup", "source_mixing", "packing"]


def test_toxic_documents_go_and_clean_ones_stay(spark):
    folder = "/root/testdata/sf0.1"
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    kept = {r.doc_id for r in cp.reject_toxic(spark, docs, folder).select("doc_id").collect()}
    rejected = {r.doc_id for r in toxicity.op7_toxicity(spark, folder).where("predicted = 1").collect()}
    assert kept == {r.doc_id for r in docs.select("doc_id").collect()} - rejected
    labels = {r.doc_id: r.toxic for r in spark.read.parquet(f"{folder}/labels.parquet").collect()}
    clean = [i for i, y in labels.items() if not y]
    assert sum(i in kept for i in clean) / len(clean) > 0.98


def test_lines_drop_and_lengths_follow(spark):
    out = {r.doc_id: r for r in cp.drop_shared_lines(spark, frame(spark), "").collect()}
    assert out[1].text == ROWS[0][1] and out[2].text.startswith("something") and out[3].text == ""
    assert out[3].n_chars == 0 and out[5].n_chars == 0 and out[2].n_chars == len(out[2].text)
    assert cp.drop_shared_lines(spark, frame(spark), "").columns == frame(spark).columns


def test_one_of_each_near_copy_stays(spark):
    rows = [*ROWS, (0, ROWS[0][1].upper(), "en", "s1", 1)]
    out = cp.keep_one_of_near_copies(spark, frame(spark, rows), "")
    fps = [simhash.fingerprint(r.text) for r in out.collect()]
    assert all((a ^ b).bit_count() > 3 for i, a in enumerate(fps) for b in fps[:i])
    assert {r.doc_id for r in out.collect()} == {0, 2, 3, 4, 5} and out.columns == frame(spark).columns


def test_mixing_repeats_rows(spark):
    docs = frame(spark)
    out = cp.mix_sources(spark, docs, "").collect()
    copies = {r.doc_id: r._mx_copies for r in mixing.rates(docs.where("text IS NOT NULL")).collect()}
    assert set(copies) == {1, 2, 3, 4} and all(sum(r.doc_id == i for r in out) <= 2 for i in copies)


def test_run_packs_what_the_stages_keep(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for _, stage in cp.STAGES[:-1]:
        docs = stage(spark, docs, sf).cache()
        assert re.match(r"doc_id,text,lang,source,n_chars$", ",".join(docs.columns))
    rows = cp.run(spark, sf).collect()
    assert sorted(r.doc_id for r in rows if r.start == 0) == sorted(r.doc_id for r in docs.select("doc_id").collect())


def test_empty_documents(spark, sf):
    docs = frame(spark).limit(0)
    for _, stage in cp.STAGES:
        docs = stage(spark, docs, sf)
        assert docs.count() == 0
        if "sequence_id" in docs.columns:
            break
