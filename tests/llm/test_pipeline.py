"""Every stage of the pipeline against a plain version of what it does, on what the stage before it kept."""

from collections import Counter

import duckdb
import numpy as np
import pytest

import corpus_pipeline
from equidepth.llm import decontaminate, mixing, probminhash, sharding, toxicity
from equidepth.llm.shared import WordHashes, shingles_of, word_hashes

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.fixture(scope="module")
def kept(spark, data, tmp_path_factory):
    """What each stage kept, the input first."""
    out = [spark.read.parquet(f"{data}/documents.parquet")]
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        path = f"{tmp_path_factory.mktemp('stage')}/{k}"
        stage(spark, out[-1], data).write.parquet(path)
        out.append(spark.read.parquet(path))
    return out


def bag(df):
    return Counter(tuple(r[c] for c in COLUMNS) for r in df.collect())


def test_stages_are_the_ones_asked_for(kept):
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "near_duplicates", "decontamination", "source_mix", "sharding"]
    assert all(df.columns == COLUMNS for df in kept[:5]) and kept[5].columns == [*COLUMNS, "shard", "slot"]


def test_toxic_documents_go(spark, data, kept):
    texts = [(r["doc_id"], r["text"] or "") for r in kept[0].collect()]
    marks = {r["doc_id"]: r["toxic"] for r in spark.read.parquet(f"{data}/labels.parquet").collect()}
    model = toxicity.train(*toxicity.labelled_texts(kept[0], spark.read.parquet(f"{data}/labels.parquet"), 6000, 30_000_000))
    scores = model.scores([t for _, t in texts], toxicity.WordHeights(model))
    gone = {d for (d, _), s in zip(texts, scores, strict=True) if s >= 0.3}
    assert bag(kept[1]) == Counter({r: n for r, n in bag(kept[0]).items() if r[0] not in gone})
    assert {d for d, m in marks.items() if m == 1} & gone


def test_one_document_of_each_class_stays(kept):
    memo, rows = WordHashes(), {r["doc_id"]: r["text"] for r in kept[1].collect()}
    sets = {d: probminhash.weighted_shingles(t, memo, 5) for d, t in rows.items()}
    ids, root = sorted(sets), {d: d for d in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if len(sets[a][0]) and len(sets[b][0]) and find(a) != find(b) and probminhash.is_near(sets[a], sets[b], probminhash.NearSpec()):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    want = {find(d) if len(sets[d][0]) else d for d in ids}
    assert {r["doc_id"] for r in kept[2].collect()} == want and kept[2].count() == len(want)


def test_documents_that_hold_an_item_go(spark, data, kept):
    memo = WordHashes()
    items = [shingles_of(word_hashes(r["text"], memo), 5) for r in spark.read.parquet(f"{data}/benchmark.parquet").collect()]

    def leaks(text):
        doc = shingles_of(word_hashes(text, memo), 5)
        for b in items:
            size = min(len(b), len(doc))
            near = np.flatnonzero(np.isin(doc, b))
            starts = {s for p in near.tolist() for s in range(max(0, p - size + 1), min(p, len(doc) - size) + 1)}
            if any(decontaminate.weighted_jaccard(doc[s : s + size], b) >= 0.8 for s in starts):
                return True
        return False

    rows = bag(kept[2])
    assert bag(kept[3]) == Counter({r: n for r, n in rows.items() if not leaks(r[1])}) and len(bag(kept[3])) < len(rows)


def test_documents_come_as_often_as_the_mix_takes_them(kept):
    c = duckdb.connect()
    c.register("documents", kept[3].toArrow())
    import hashlib

    taken = {r[0]: (r[1], r[4]) for r in c.execute(mixing.OP5_SQL).fetchall()}
    want = Counter()
    for row, n in bag(kept[3]).items():
        size, words = taken[row[0]]
        part = int(hashlib.md5(f"round/{row[0]}".encode()).hexdigest()[:8], 16) / 2**32
        copies = int(words / size + part) if words else 0
        if copies:
            want[row] = copies * n
    assert bag(kept[4]) == want


def test_what_the_mix_holds_is_dealt_evenly(kept):
    rows = kept[5].collect()
    assert bag(kept[5]) == bag(kept[4])
    held = [sorted(r["slot"] for r in rows if r["shard"] == s) for s in range(24)]
    assert [len(h) for h in held] == sharding.capacities(len(rows), 24, 0.0, True) and all(h == list(range(len(h))) for h in held)


def test_run_gives_the_last_stage(spark, data, kept):
    got = corpus_pipeline.run(spark, data)
    assert sorted(map(repr, (tuple(r) for r in got.collect()))) == sorted(map(repr, (tuple(r) for r in kept[5].collect())))
