"""Nulls, empty and very long texts, ties, repeated rows, empty tables and clashing columns, for every operator and stage."""

import uuid

import pytest

import corpus_pipeline
from equidepth.llm import bottomk, decontaminate, html_crf, line_dedup, lm_scoring, mixing, probminhash, sharding, token_counts, toxicity
from equidepth.llm.shared import work_dir

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, uid string, score double, size int, shard string, _k int, c0 string, copies int"
LONG = " ".join(f"word{i % 977} und{i % 53}" for i in range(40_000))


def row(i, text, source="a"):
    return (i, text, "en", source, None if text is None else len(text), "u", 0.5, 7, "s", 3, "c", 9)


ROWS = [row(1, None), row(2, ""), row(3, "   \n\t "), row(None, "no id here but some text in it"), row(4, "one two three four five six seven", None), row(4, "one two three four five six seven", None), row(5, LONG), row(6, "x"), row(7, "…!?"), row(None, None, None), row(8, "one two three four five six seven")]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def items(spark):
    return spark.createDataFrame([(1, None), (2, ""), (3, "alpha beta gamma delta epsilon zeta eta theta"), (None, "x y")], "item_id long, text string")


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(5, 1, 0), (6, None, None), (None, 0, 1)], "doc_id long, quality int, toxic int")


def test_shards(docs, none):
    got = sharding.assign_shards(docs, 3).collect()
    sizes = sorted(sum(r["shard"] == s for r in got) for s in range(3))
    assert len(got) == len(ROWS) and sizes[-1] - sizes[0] <= 1
    for s in range(3):
        assert sorted(r["slot"] for r in got if r["shard"] == s) == list(range(sum(r["shard"] == s for r in got)))
    assert sharding.assign_shards(none, 3).count() == 0
    by_bytes = sharding.assign_shards(docs, 3, load="bytes", slack=0.1).collect()
    assert len(by_bytes) == len(ROWS) and "_k" in by_bytes[0].asDict()


def test_lm(docs, none, spark):
    spec = lm_scoring.LmSpec(words=50, bands=2, kinds=4, classes=5, slots=1 << 10)
    net, rows = lm_scoring.fit(docs, spec)
    got = {(r["doc_id"], r["n_tokens"]): r for r in lm_scoring.score(rows, net).collect()}
    assert lm_scoring.score(rows, net).count() == len(ROWS)
    assert got[(1, 0)]["log_likelihood"] == 0 and got[(1, 0)]["mean_log_prob"] is None and got[(5, 80_000)]["log_likelihood"] < 0
    net, rows = lm_scoring.fit(none, spec)
    assert lm_scoring.score(rows, net).count() == 0


def test_html(spark):
    rows = [(1, None, "u"), (2, "", None), (None, "<p>Some text here, quite long enough to be an article of its own.", "x"), (4, "<div><p>" + "A sentence. " * 20_000 + "</p></div>", "y"), (5, "<<<>>><a", "z")]
    pages = spark.createDataFrame(rows, "page_id long, html string, main_text string")
    got = html_crf.extract(pages).collect()
    assert len(got) == 5 and all(r["main_text"] is not None for r in got)
    assert next(r for r in got if r["page_id"] == 4)["main_text"].count("A sentence.") in (0, 20_000)
    assert html_crf.extract(pages.limit(0)).count() == 0


def test_near(docs, none):
    got = probminhash.near_classes(docs).collect()
    assert len(got) == len(ROWS)
    same = {r["class_id"] for r in got if r["doc_id"] in (4, 8)}
    assert same == {4}
    assert {r["class_id"] for r in got if r["doc_id"] in (1, 2, 3, 7)} == {1, 2, 3, 7}
    kept = probminhash.keep_one(docs)
    assert kept.columns == docs.columns and kept.count() == len(ROWS) - 2 and kept.filter("uid = 'u' AND c0 = 'c'").count() == len(ROWS) - 2
    assert probminhash.near_classes(none).count() == 0 and probminhash.keep_one(none).count() == 0


def test_near_classes_of_one_least_id(spark):
    """Different texts stay apart where their doc_ids are null or the same; equal texts still are one class."""
    rows = [row(None, "alpha beta gamma delta epsilon zeta"), row(None, "red green blue black white grey"), row(None, "red green blue black white grey"), row(3, "one two three four five six"), row(3, "mon tue wed thu fri sat")]
    docs = spark.createDataFrame(rows, SCHEMA)
    assert sorted(r["text"] for r in probminhash.keep_one(docs).collect()) == sorted({r[1] for r in rows})
    assert probminhash.near_classes(docs).select("root").distinct().count() == 4


def test_mix(docs, none):
    rows, slots, _ = mixing.mix(docs, block_words=16)
    got = rows.collect()
    assert len(got) == len(ROWS) and all(0 <= r["taken"] <= 2 * r["size"] for r in got)
    assert {r["size"] for r in got if r["doc_id"] in (1, 2, 3)} == {0}
    mixed = mixing.mixed_documents(docs, block_words=16)
    assert mixed.columns == docs.columns and mixed.filter("doc_id IN (1, 2, 3)").count() == 0
    assert mixing.mix(none)[0].count() == 0 and mixing.mixed_documents(none).count() == 0


def test_leaks(docs, none, items, spark):
    assert decontaminate.find_leaks(docs, items).count() == 0
    more = docs.unionByName(spark.createDataFrame([row(None, f"{LONG} Alpha beta gamma, delta epsilon zeta eta theta {LONG}"), row(9, "alpha beta gamma delta epsilon zeta eta theta")], SCHEMA))
    found = decontaminate.find_leaks(more, items).collect()
    assert sorted((r["row"] is None, r["item_id"], r["similarity"]) for r in found) == [(False, 3, 1.0), (True, 3, 1.0)]
    clean = decontaminate.without_leaks(more, items)
    assert clean.columns == docs.columns and clean.count() == len(ROWS)
    assert decontaminate.find_leaks(none, items).count() == 0 and decontaminate.find_leaks(docs, items.limit(0)).count() == 0 and decontaminate.without_leaks(none, items).count() == 0


def test_lines(docs, none):
    got = line_dedup.drop_boilerplate(docs, "source", min_pages=2, max_ratio=0.5).collect()
    assert len(got) == len(ROWS) and [r["text"] for r in got if r["doc_id"] == 1] == [None]
    assert {r["text"] for r in got if r["doc_id"] == 4} == {""} and {r["n_dropped"] for r in got if r["doc_id"] == 4} == {1}
    wide = line_dedup.drop_boilerplate(docs, "source", min_pages=2, max_ratio=0.5, broadcast_rows=0).collect()
    assert sorted(map(repr, got)) == sorted(map(repr, wide))
    assert line_dedup.drop_boilerplate(none, "source").count() == 0


def test_tokens(docs, none, spark):
    import public_tokenizers

    spec = token_counts.TokenizerSpec(public_tokenizers.path("word_bpe_49k.json"), True)
    cache = f"{work_dir(spark)}/cache-edges-{uuid.uuid4().hex}"
    got = {(r["doc_id"], r["n_bytes"]): r["n_tokens"] for r in token_counts.count_tokens(docs, spec, cache).collect()}
    assert got[(1, 0)] == 0 and got[(3, 6)] == 0 and got[(8, 33)] == 7
    assert token_counts.count_tokens(none, spec, cache).count() == 0


def test_fingerprints(docs, none, spark):
    got = bottomk.fingerprint_edits(docs).collect()
    assert len(got) == len(ROWS) and all(0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1 for r in got)
    same = {r["fingerprint"] for r in got if r["doc_id"] in (4, 8)}
    assert len(same) == 1 and {r["fingerprint"] for r in got if r["doc_id"] in (1, 2, 3)} == {""}
    one = bottomk.fingerprint_edits(docs.filter("doc_id = 8")).first()
    assert one["near_next"] == 1.0 and one["edited_sha256"] is not None
    assert bottomk.fingerprint_edits(none).count() == 0


def test_toxic(docs, none, labels):
    model = toxicity.fit(docs, labels)
    got = toxicity.score_texts(docs, model).collect()
    assert len(got) == len(ROWS) and all(0 <= r["score"] <= 1 for r in got)
    kept = toxicity.clean_documents(docs, labels)
    assert kept.columns == docs.columns
    assert toxicity.clean_documents(none, labels.limit(0)).count() == 0


def test_stages(docs, none, spark, tmp_path, labels, items):
    labels.write.parquet(f"{tmp_path}/labels.parquet")
    items.write.parquet(f"{tmp_path}/benchmark.parquet")
    for start in (docs, none):
        df = start
        for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
            path = f"{tmp_path}/{start is docs}-{i}"
            out = stage(spark, df, str(tmp_path))
            assert out.columns[: len(docs.columns)] == docs.columns if i < 4 else {"shard", "slot"} <= set(out.columns), name
            out.write.parquet(path)
            df = spark.read.parquet(path)
        assert (df.count() > 0) == (start is docs)


def operators(spark, df, items, labels):
    """Rows of every operator's result, by its number."""
    import public_tokenizers

    spec = token_counts.TokenizerSpec(public_tokenizers.path("word_bpe_49k.json"), True)
    net, rows = lm_scoring.fit(df, lm_scoring.LmSpec(words=50, bands=2, kinds=4, classes=5, slots=1 << 10))
    found = {
        1: sharding.assign_shards(df, 3), 2: lm_scoring.score(rows, net), 4: probminhash.near_classes(df), 5: mixing.mix(df)[0], 6: decontaminate.without_leaks(df, items),
        7: line_dedup.drop_boilerplate(df, "source"), 8: token_counts.count_tokens(df, spec, f"{work_dir(spark)}/cache-{uuid.uuid4().hex}"), 9: bottomk.fingerprint_edits(df), 10: toxicity.score_texts(df, toxicity.fit(df, labels)),
    }
    return {k: v.collect() for k, v in found.items()}


def test_rows_of_nulls_alone(spark, items, labels):
    df = spark.createDataFrame([(None,) * 12] * 7, SCHEMA)
    got = operators(spark, df, items, labels)
    assert all(len(r) == 7 for r in got.values())
    assert probminhash.keep_one(df).count() == 7 and mixing.mixed_documents(df).count() == 0 and toxicity.clean_documents(df, labels).count() == 7
    pages = spark.createDataFrame([(None, None, None)] * 3, "page_id long, html string, url string")
    assert [r["main_text"] for r in html_crf.extract(pages).collect()] == [""] * 3


def test_one_huge_token(spark, items, labels):
    token = "abcdefghij" * 100_000
    df = spark.createDataFrame([row(1, token), row(2, token), row(3, f"{token}k"), row(4, "some other words that stand here")], SCHEMA)
    got = operators(spark, df, items, labels)
    assert all(len(r) == 4 for r in got.values())
    classes = {r["doc_id"]: r["class_id"] for r in got[4]}
    assert classes == {1: 1, 2: 1, 3: 3, 4: 4}
    assert {r["doc_id"]: r["n_bytes"] for r in got[8]}[3] == 1_000_001
    page = spark.createDataFrame([(1, f"<article><p>{token}</p></article>")], "page_id long, html string")
    assert len(html_crf.extract(page).first()["main_text"]) in (0, len(token))
