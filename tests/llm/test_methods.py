"""Each method against brute force, an exact round trip or held-out accuracy."""

import hashlib
import os
import re
import struct
import uuid
import zlib

import duckdb
import numpy as np
import pyarrow as pa
import pytest
import xxhash

from equidepth.llm import bottomk, decontaminate, html_crf, line_dedup, lm_scoring, mixing, probminhash, queries, sharding, token_counts, toxicity
from equidepth.llm.html_blocks import blocks_of
from equidepth.llm.shared import WordHashes, shingles_of, word_hashes, work_dir


@pytest.fixture(scope="module")
def docs(spark, data):
    return spark.read.parquet(f"{data}/documents.parquet")


@pytest.fixture(scope="module")
def texts(docs):
    return {r["doc_id"]: r["text"] for r in docs.select("doc_id", "text").collect()}


@pytest.mark.parametrize("name", sorted(queries.ORACLE_SQL))
def test_sql(spark, data, name):
    c = duckdb.connect()
    for t in ("documents", "pages", "labels", "benchmark"):
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{data}/{t}.parquet')")
    df = queries.QUERIES[name](spark, data)
    cur = c.execute(queries.ORACLE_SQL[name])
    at = [[d[0] for d in cur.description].index(n) for n in df.columns]
    assert sorted(repr(tuple(r)) for r in df.collect()) == sorted(repr(tuple(r[i] for i in at)) for r in cur.fetchall())


# ---- 1


def test_ring_keeps_most_rows_when_it_grows(docs):
    a = {r["doc_id"]: r["shard"] for r in sharding.assign_shards(docs, 8, slack=0.25).collect()}
    b = {r["doc_id"]: r["shard"] for r in sharding.assign_shards(docs, 9, slack=0.25).collect()}
    moved = sum(a[k] != b[k] for k in a) / len(a)
    assert moved < 0.4 < 8 / 9  # a plain modulus would move about 8 of 9
    assert max(np.bincount(list(a.values()))) <= np.ceil(1.25 * len(a) / 8)


def test_walk_fills_exactly_and_overflow_goes_on_clockwise():
    ring = sharding.Ring(3, 4, cells=64)
    loads = {(c, 0): 5 for c in range(64)}
    caps = sharding.capacities(320, 3, 0.0, True)
    pieces = sharding.walk(ring, loads, caps)
    held = [0] * 3
    for _, _, a, b, s in pieces:
        held[s] += b - a
    assert held == caps
    nodes = ring.owners()
    for cell in range(64):  # a cell's first piece is its own shard's unless that was full
        home = nodes[np.searchsorted(nodes[:, 0], cell) % len(nodes), 1]
        first = next(p for p in pieces if p[0] == cell)
        assert first[4] == home or not any(p[0] == cell and p[4] == home for p in pieces)


def test_shards_of_every_row_by_the_rule(spark, data, docs):
    """Sizes, digests and slots by definition; a row stands at its ring point's shard or past shards that are full."""
    rows = {r["doc_id"]: r for r in sharding.op1_query(spark, data).collect()}
    texts = {r["doc_id"]: r["text"] or "" for r in docs.select("doc_id", "text").collect()}
    assert rows.keys() == texts.keys()
    caps = sharding.capacities(len(texts), 24, 0.0, True)
    held = [sorted(r["slot"] for r in rows.values() if r["shard"] == s) for s in range(24)]
    assert [len(h) for h in held] == caps and all(h == list(range(len(h))) for h in held)
    ring = sharding.Ring(24)
    nodes, bits = ring.owners(), (ring.cells - 1).bit_length()
    for d, r in rows.items():
        body = texts[d].encode()
        assert r["size"] == len(body) + 8 and r["text_crc32"] == zlib.crc32(body) and r["law"] == "rows" and r["grown_shard"] is None
        point = xxhash.xxh64_intdigest(struct.pack("<q", d), seed=xxhash.xxh64_intdigest(struct.pack("<i", ring.seed), seed=42))
        at = int(np.searchsorted(nodes[:, 0], point >> (64 - bits))) % len(nodes)
        passed = set()
        while nodes[at, 1] != r["shard"]:
            passed.add(int(nodes[at, 1]))
            at = (at + 1) % len(nodes)
        assert all(len(held[s]) == caps[s] for s in passed)


def test_a_key_of_a_third_of_all_rows_is_spread(spark):
    rows = [(7 if i % 3 == 0 else i, f"text {i}") for i in range(3000)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sharding.assign_shards(df, 5, rows_per_sub=50).collect()
    assert sorted(np.bincount([r["shard"] for r in got])) == [600] * 5
    for s in range(5):
        assert sorted(r["slot"] for r in got if r["shard"] == s) == list(range(600))


# ---- 2


SMALL = lm_scoring.LmSpec(words=199, bands=4, kinds=4, slots=1 << 12, classes=12, rounds=3, hidden=8, batch=256, shard_tokens=20_000)


def test_log_probabilities_by_definition_and_training_helps(docs, texts):
    net, rows = lm_scoring.fit(docs, SMALL)
    pairs = [net.v.encode(t) for t in list(texts.values())[:20]]
    coded = [ids for ids, _ in pairs]
    context, target, _ = lm_scoring.windows(coded, SMALL)
    got = net.log_prob(context, target)
    for k in range(0, len(target), 997):
        h = np.tanh(net.bias + sum(net.tables[i][context[k, i]] for i in range(context.shape[1])))
        cls = net.v.of[target[k]]
        z = h @ net.cls + net.cls_b
        own = np.flatnonzero(net.v.of == cls)
        y = net.tok[own] @ h + net.tok_b[own]
        want = z[cls] - np.log(np.exp(z).sum()) + y[list(own).index(target[k])] - np.log(np.exp(y).sum())
        assert got[k] == pytest.approx(want, abs=1e-4)
    total = np.exp(net.log_prob(np.repeat(context[:1], SMALL.size, 0), np.arange(SMALL.size))).sum()
    assert total == pytest.approx(1, abs=1e-4)
    assert got.mean() > lm_scoring.Network(net.v).log_prob(context, target).mean() + 0.1
    scored = {r["doc_id"]: r for r in lm_scoring.score(rows, net).collect()}
    first = next(iter(texts))
    assert scored[first]["n_tokens"] == len(coded[0]) and scored[first]["log_likelihood"] == pytest.approx(got[: len(coded[0])].sum() + pairs[0][1], rel=1e-4)


def test_probabilities_over_all_tokens_of_the_corpus_sum_to_one(docs, texts):
    """Each token's share in its unit: over the unit's tokens they sum to one; the counts are those of the corpus."""
    from collections import Counter

    vocabulary, total = lm_scoring.corpus_vocabulary(docs, SMALL)
    counts = Counter(w for t in texts.values() for w in t.lower().split())
    assert total == sum(counts.values())
    assert [w for w, _ in sorted(counts.items(), key=lambda x: (-x[1], x[0]))[: SMALL.words]] == sorted(vocabulary.ids, key=vocabulary.ids.get)
    sums, mass = np.zeros(SMALL.size), np.zeros(SMALL.size)
    for w, n in counts.items():
        ids, share = vocabulary.encode(w)
        sums[ids[0]] += np.exp(share)
        mass[ids[0]] += n
    assert mass == pytest.approx(vocabulary.mass) and sums[mass > 0] == pytest.approx(1, rel=1e-3)


def test_scores_do_not_depend_on_partitions(docs):
    one, many = (lm_scoring.score(*reversed(lm_scoring.fit(docs.repartition(n), SMALL))).collect() for n in (1, 32))
    a, b = ({r["doc_id"]: r["mean_log_prob"] or 0.0 for r in x} for x in (one, many))
    assert a.keys() == b.keys() and max(abs(a[k] - b[k]) for k in a) < 1e-6


def test_gain_over_single_token_counts_on_texts_it_has_not_seen(spark):
    from pyspark.sql import functions as F

    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    held = docs.filter("doc_id % 10 = 0")
    net, _ = lm_scoring.fit(docs.filter("doc_id % 10 <> 0"))
    rows = lm_scoring.encoded(held, net.v, keys=("doc_id",))
    trained, counts = (lm_scoring.score(rows, n).agg(F.sum("log_likelihood") / F.sum("n_tokens")).first()[0] for n in (net, lm_scoring.Network(net.v)))
    assert trained > counts + 0.3


def test_every_position_is_a_target_once():
    """Over the rounds each token of each text is learned from once, however short or long the text and whatever stands beside it."""
    spec = lm_scoring.LmSpec(words=20, bands=1, kinds=2, classes=4)
    none = np.zeros(0, np.int64)
    vocabulary = lm_scoring.make_vocabulary([(f"w{i}", 20 - i) for i in range(20)], none, none.astype(float), none, 16, spec)
    texts = ["w1", "w2 w3", " ".join(f"w{i % 20}" for i in range(50)), "", "w4 w5 w6", "w7 " * (lm_scoring.POSITIONS + 7)]
    flat, learned = lm_scoring.Network(vocabulary).flat, 0
    ids = [vocabulary.encode(t)[0].tobytes() for t in texts]
    for turn in range(spec.rounds):
        for batch in lm_scoring._trained(iter([pa.RecordBatch.from_arrays([pa.array(ids, pa.binary())], names=["_ids"])]), flat, vocabulary.units(), turn):
            learned += batch.column("n")[0].as_py()
    assert learned == sum(len(t.split()) for t in texts)


def test_pieces_of_a_long_text_are_its_windows():
    spec = lm_scoring.LmSpec()
    text = np.random.default_rng(0).integers(0, 4000, 1003).astype(np.uint16)
    context, target, _ = lm_scoring.windows([text], spec)
    parts = list(lm_scoring.pieces_of(text, spec, 100))
    assert (np.concatenate([c for c, _, _ in parts]) == context).all() and (np.concatenate([t for _, t, _ in parts]) == target).all()
    assert [f for _, _, f in parts] == list(range(0, 1003, 100))


# ---- 3


def test_field_on_pages_it_has_not_seen():
    model, memo, wrong, total = html_crf.train(), {}, 0, 0
    for blocks, marks in html_crf.labelled(html_crf.CrfSpec(pages=120, seed=991)):
        got = model.decode(blocks, memo)
        wrong += sum(a != b for a, b in zip(got, marks, strict=True))
        total += len(marks)
    assert wrong / total < 0.01


def test_viterbi_is_the_best_path():
    model, memo = html_crf.train(), {}
    r = np.random.default_rng(1)
    blocks = blocks_of("".join(f"<{t}>{'word ' * n}</{t}>" for t, n in zip(r.choice(["p", "div", "li", "h2"], 9), r.integers(1, 30, 9), strict=True)))
    lift = [sum(float(model.weights[html_crf._at(f)]) for f in (*html_crf.path_features(b.path), *html_crf.text_features(b, i, len(blocks)))) for i, b in enumerate(blocks)]

    def score(ys):
        s = model.start[ys[0]] + lift[0] * ys[0]
        for i in range(1, len(ys)):
            same = int(html_crf.parent_of(blocks[i].path) is html_crf.parent_of(blocks[i - 1].path))
            s += model.moves[same, ys[i - 1], ys[i]] + lift[i] * ys[i]
        return s

    best = max(([int(c) for c in f"{k:0{len(blocks)}b}"] for k in range(2 ** len(blocks))), key=score)
    assert score(model.decode(blocks, memo)) == pytest.approx(score(best))


def test_article_of_the_given_pages(spark, data):
    rows = spark.read.parquet(f"{data}/pages.parquet").select("page_id", "html").collect()
    want = {r["page_id"]: "\n".join(b.text for b in blocks_of(r["html"]) if any(n.tag == "article" for n in b.path.up())) for r in rows}
    got = {r["page_id"]: r["text"] for r in html_crf.op3_query(spark, data).collect()}
    assert got == want


def test_blocks_of_rough_html():
    html = "<p>One <b>two<br>three</b>\n four &amp; &#233;&nbsp;x<p>Five</p><script>var a='</p>'</script><ul><li>a<li>b</ul><!-- no --><td>c"
    assert [b.text for b in blocks_of(html)] == ["One two three four & é x", "Five", "a", "b", "c"]


def test_quotes_end_where_browsers_end_them():
    assert [b.text for b in blocks_of("<p title=it's>a</p><p class='x>y'>b</p><p data-x = \"1>2\"class=z>c</p><p =x>d</p><p a=b=\"c>e</p>")] == ["a", "b", "c", "d", "e"]
    assert [b.text for b in blocks_of('<p>before</p><p class="x>text</p><p>more')] == ["before"]  # the value never ends
    assert [b.text for b in blocks_of('<p class="x>text</p><p id="y">after</p>')] == ["after"]


def test_deep_and_rough_pages_cost_what_they_hold():
    import time
    import tracemalloc

    deep = "".join(f"<div class=c{i % 5000}>x" for i in range(60_000)) + "</q></p></li></zz>" * 20_000
    model = html_crf.train()
    tracemalloc.start()
    began = time.process_time()
    model.text(deep, {})
    assert time.process_time() - began < 60 and tracemalloc.get_traced_memory()[1] < 400e6
    tracemalloc.stop()


# ---- 4


def test_probability_jaccard_and_its_signature(texts):
    memo = WordHashes()
    sets = [probminhash.weighted_shingles(t, memo, 5) for t in list(texts.values())[:80]]

    def brute(a, b):
        x, y = dict(zip(a[0].tolist(), a[1] / a[1].sum(), strict=True)), dict(zip(b[0].tolist(), b[1] / b[1].sum(), strict=True))
        return sum(1 / sum(max(x.get(e, 0) / x[d], y.get(e, 0) / y[d]) for e in {*x, *y}) for d in {*x} & {*y})

    r = np.random.default_rng(0)
    a = (np.arange(60, dtype=np.uint64), r.integers(1, 9, 60).astype(float))
    b = (np.arange(20, 90, dtype=np.uint64), r.integers(1, 9, 70).astype(float))
    want = brute(a, b)
    assert probminhash.probability_jaccard(a, b) == pytest.approx(want)
    sig = probminhash.signatures([a, b], 20_000, 5)
    assert (sig[0] == sig[1]).mean() == pytest.approx(want, abs=0.02)
    assert probminhash.probability_jaccard(sets[0], sets[0]) == pytest.approx(1.0)


def test_classes_equal_brute_force(spark, data, texts):
    memo = WordHashes()
    sets = {d: probminhash.weighted_shingles(t, memo, 5) for d, t in texts.items()}
    ids, root = sorted(sets), {d: d for d in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if len(np.intersect1d(sets[a][0][:50], sets[b][0])) or len(np.intersect1d(sets[b][0][:50], sets[a][0])):
                if probminhash.probability_jaccard(sets[a], sets[b]) >= 0.8:
                    x, y = find(a), find(b)
                    root[max(x, y)] = min(x, y)
    got = {r["doc_id"]: r["class_id"] for r in probminhash.op4_query(spark, data).collect()}
    assert got == {d: find(d) for d in ids}


def test_a_hub_of_many_copies(spark):
    """Copies near one base but not near each other are one class; nothing is lost to the choice of hubs."""
    base = [f"w{i}" for i in range(120)]
    rows = [(0, " ".join(base))]
    for k in range(1, 60):
        words = list(base)
        words[(k * 2) % 110] = f"x{k}"
        words[(k * 2 + 40) % 110] = f"y{k}"
        rows.append((k, " ".join(words)))
    rows += [(100 + k, " ".join(f"z{k}_{i}" for i in range(50))) for k in range(20)]
    got = {r["doc_id"]: r["class_id"] for r in probminhash.near_classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert {got[k] for k in range(60)} == {0} and all(got[100 + k] == 100 + k for k in range(20))


def test_text_near_one_variant_that_is_not_the_hub(spark):
    """A variant with a tail, near that variant alone, joins its class."""
    memo, rows, tails = WordHashes(), [], {}
    for g in range(5):
        base = [f"g{g}w{i}" for i in range(400)]
        variants = [" ".join([*base[: 20 + 9 * v], f"v{v}", *base[21 + 9 * v :]]) for v in range(40)]
        tail = f"{variants[17]} " + " ".join(f"g{g}t{i}" for i in range(90))
        sets = [probminhash.weighted_shingles(t, memo, 5) for t in variants]
        end = probminhash.weighted_shingles(tail, memo, 5)
        assert [v for v in range(40) if probminhash.probability_jaccard(sets[v], end) >= 0.8] == [17]
        rows += [(1000 * g + v, t) for v, t in enumerate(variants)] + [(1000 * g + 900, tail)]
        tails[1000 * g + 900] = 1000 * g
    got = {r["doc_id"]: r["class_id"] for r in probminhash.near_classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert {d: got[d] for d in tails} == tails and set(got.values()) == set(tails.values())


@pytest.mark.parametrize("block", [16, 512])
def test_groups_in_one_bucket_and_chains(spark, monkeypatch, block):
    """Two large groups of variants of which one's hub is foreign to the other, and a chain whose ends are far apart: every class whole, few links."""
    r = np.random.default_rng(3)

    def edited(words, share, tag):
        out = list(words)
        for k in r.choice(len(out), int(len(out) * share), replace=False):
            out[k] = f"{tag}{k}"
        return out

    monkeypatch.setattr(probminhash, "BLOCK", block)
    base = [f"w{i}" for i in range(300)]
    other = base[:200] + [f"o{i}" for i in range(100)]  # half of its shingles' weight and more lies in the first group
    rows = [(k, " ".join(edited(base, 0.01, f"a{k}_"))) for k in range(200)] + [(1000 + k, " ".join(edited(other, 0.01, f"b{k}_"))) for k in range(200)]
    link = [f"c{i}" for i in range(400)]
    for k in range(60):
        link = link[10:] + [f"n{k}_{i}" for i in range(10)]
        rows.append((2000 + k, " ".join(link)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {x["doc_id"]: x["class_id"] for x in probminhash.near_classes(df).collect()}
    memo = WordHashes()
    sets = {d: probminhash.weighted_shingles(t, memo, 5) for d, t in rows}
    root = {d: d for d in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(sorted(sets)):
        for b in sorted(sets)[i + 1 :]:
            if find(a) != find(b) and probminhash.is_near(sets[a], sets[b], probminhash.NearSpec()):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    assert got == {d: find(d) for d in sets} and len(set(got.values())) == 3
    _, joins = probminhash.near_links(df)
    assert joins.count() < 28 * len(rows)


def test_components_either_way(spark):
    """Paths, stars and cycles: the least name of each component, by broadcast and from checkpoints."""
    r = np.random.default_rng(6)
    edges = [(i, i + 1) for i in range(40)] + [(100, 100 + i) for i in range(1, 60)] + [(300 + i, 300 + (i + 1) % 15) for i in range(15)] + [(400 + a, 400 + b) for a, b in r.integers(0, 60, (45, 2))]
    label = {x: x for e in edges for x in e}
    for _ in label:
        for a, b in edges:
            label[a] = label[b] = min(label[a], label[b])
    df = spark.createDataFrame([(a.to_bytes(2, "big"), b.to_bytes(2, "big")) for a, b in (map(int, e) for e in edges)], "a binary, b binary")
    for few in (0, 100_000):
        got = {int.from_bytes(x["uid"], "big"): int.from_bytes(x["root"], "big") for x in probminhash.components(df, few).collect()}
        assert got == {x: m for x, m in label.items() if m != x}
    assert probminhash.components(df.limit(0)).count() == 0


def test_joins_by_postings_equal_pairs_one_by_one():
    """The block comparison gives the same components as comparing every pair, with weights too."""
    r = np.random.default_rng(8)
    spec = probminhash.NearSpec()
    bags = []
    for g in range(6):
        base = np.sort(r.choice(5000, 80, replace=False)).astype(np.uint64)
        for _ in range(5):
            own = np.unique(np.concatenate([r.choice(base, 77, replace=False), r.choice(5000, 2).astype(np.uint64)]))
            bags.append((own, r.integers(1, 3, len(own)).astype(float) if g % 2 else np.ones(len(own))))
    names = [bytes([i]) for i in range(len(bags))]

    def parts(pairs):
        label = list(range(len(bags)))
        for i, j in pairs:
            a, b = label[i], label[j]
            label = [a if x == b else x for x in label]
        return {tuple(np.flatnonzero(np.array(label) == x)) for x in set(label)}

    every = [(i, j) for i in range(len(bags)) for j in range(i + 1, len(bags)) if probminhash.probability_jaccard(bags[i], bags[j]) >= spec.threshold]
    assert len(every) > 10
    found = probminhash.joins(names, bags, len(bags), spec)
    assert parts(found) == parts(every) and len(found) == len(bags) - len(parts(every))
    across = probminhash.joins(names, bags, 12, spec)
    assert all(i < 12 <= j for i, j in across) and parts(across) == parts([(i, j) for i, j in every if i < 12 <= j])


# ---- 5


def test_mix_reaches_targets_and_reruns_agree(spark, data):
    a, b = mixing.op5_query(spark, data).collect(), mixing.op5_query(spark, data).collect()
    assert sorted(map(tuple, a)) == sorted(map(tuple, b))
    assert all(r["taken"] <= 2 * r["size"] for r in a)
    total = sum(r["size"] for r in a)
    groups = {}
    for r in a:
        g = groups.setdefault((r["source_size"], r["target"]), [0, 0])
        g[0] += r["taken"]
    for (size, target), (taken, _) in groups.items():
        assert target <= 2 * size and abs(taken - target) <= 256
    assert sum(t for _, t in groups) == pytest.approx(1.5 * total)


def test_targets_of_many_sources_by_slices(spark):
    """What slices give for more sources than one task should hold is what windows give."""
    from pyspark.sql import functions as F

    df = spark.range(5000).select(F.concat(F.lit("1s"), (F.col("id") % 700).cast("string")).alias("src"), (F.col("id") * 37 % 1013).alias("size"))
    one, many = ({r["src"]: (r["source_size"], r["target"]) for r in mixing.source_targets(df, one_task=n).collect()} for n in (1000, 10))
    assert one.keys() == many.keys() and all(one[k][0] == many[k][0] and one[k][1] == pytest.approx(many[k][1]) for k in one)
    total = sum(s for s, _ in one.values())
    assert sum(t for _, t in one.values()) == pytest.approx(1.5 * total) and all(t <= 2 * s for s, t in one.values())


def test_block_permutation_is_one(spark):
    from pyspark.sql import functions as F

    for n in (1, 2, 7, 1000):
        df = spark.range(2 * n).select(F.col("id").alias("j"), F.lit(n).cast("long").alias("blocks"), F.lit("1src").alias("src"))
        got = [r[0] for r in df.orderBy("j").select(mixing.block_of("j", "blocks", "src")).collect()]
        assert sorted(got[:n]) == list(range(n)) and sorted(got[n:]) == list(range(n))


def test_draws_over_shards_are_multinomial(docs):
    """A source's slots over the shards: their counts sum to its slots and lie within five standard errors of even shares."""
    rows, slots, _ = mixing.mix(docs, block_words=8, shard_slots=100)
    counts = {}
    for r in slots.groupBy("src", "shard").count().collect():
        counts.setdefault(r["src"], {})[r["shard"]] = r["count"]
    shards = 1 + max(s for c in counts.values() for s in c)
    assert shards > 5
    for c in counts.values():
        n = sum(c.values())
        assert all(abs(c.get(s, 0) - n / shards) <= 5 * (n / shards) ** 0.5 + 1 for s in range(shards))
    assert all((r["taken"] > 0) == (r["first_shard"] is not None) and (r["first_shard"] or 0) <= (r["last_shard"] or 0) for r in rows.collect())


# ---- 6


def test_every_planted_passage_is_found(spark, data, texts):
    items = {r["item_id"]: r["text"] for r in spark.read.parquet(f"{data}/benchmark.parquet").collect()}
    want = {(d, i) for d, t in texts.items() for i, b in items.items() if b in t}
    found = decontaminate.op6_query(spark, data).collect()
    assert want <= {(r["doc_id"], r["item_id"]) for r in found}
    memo = WordHashes()
    for r in found:
        a = shingles_of(word_hashes(texts[r["doc_id"]], memo), 5)
        b = shingles_of(word_hashes(items[r["item_id"]], memo), 5)
        assert decontaminate.weighted_jaccard(a[r["start_word"] : r["start_word"] + len(b)], b) == pytest.approx(r["similarity"]) and r["similarity"] >= 0.8


def test_windows_equal_brute_force_with_edits():
    r = np.random.default_rng(4)
    words = [f"w{i}" for i in range(400)]
    items = [(k, " ".join(r.choice(words, r.integers(40, 70)))) for k in range(30)]
    index = decontaminate.build_index(items, decontaminate.LeakSpec())
    memo = WordHashes()
    for k, text in items:
        edited = text.split()
        edited[len(edited) // 2] = "changed"
        doc = shingles_of(word_hashes(" ".join([*r.choice(words, 50), *edited, *r.choice(words, 50)]), memo), 5)
        want = set()
        for i, bag in enumerate(index.bags):
            best = max(decontaminate.weighted_jaccard(doc[s : s + len(bag)], bag) for s in range(len(doc) - len(bag) + 1))
            if best >= 0.8:
                want.add(i)
        assert {m[0] for m in index.matches(doc)} == want
        assert k in want or len(index.bags[k]) < 45


def test_a_long_text_is_searched_in_spans(monkeypatch):
    """However its windows are cut into spans, what is found is the same."""
    r = np.random.default_rng(9)
    words = [f"w{i}" for i in range(60)]
    items = [(k, " ".join(r.choice(words, 45))) for k in range(12)]
    text = " ".join([*r.choice(words, 3000), items[3][1], *r.choice(words, 2000), items[8][1], *r.choice(words, 500)])
    index = decontaminate.build_index(items, decontaminate.LeakSpec())
    doc = shingles_of(word_hashes(text, WordHashes()), 5)
    whole = index.matches(doc)
    monkeypatch.setattr(decontaminate, "SPAN", 100)
    monkeypatch.setattr(decontaminate, "CELLS", 50)
    assert sorted(index.matches(doc)) == sorted(whole) and {m[0] for m in whole} == {3, 8}


def test_radius_is_guaranteed():
    r = np.random.default_rng(0)
    spec = decontaminate.LeakSpec()
    for _ in range(300):
        a = r.integers(0, 256, 8)
        flips = r.choice(64, spec.radius, replace=False)
        b = a.copy()
        for f in flips:
            b[f // 8] ^= 1 << (f % 8)
        assert (decontaminate._POP8[a ^ b] <= spec.block_bits).any()


# ---- 7


def test_host_of(spark):
    from pyspark.sql import functions as F

    rows = [("http://A.b.com:80/x", "a.b.com"), ("https://u@h.org/?q", "h.org"), ("nothing", None), (None, None)]
    df = spark.createDataFrame(rows, "u string, h string").select(line_dedup.host_of(F.col("u")).alias("g"), "h")
    assert all(r["g"] == r["h"] for r in df.collect())


def test_lines_are_judged_by_their_own_host(spark):
    rows = [(i, "menu\nown %d" % i, "a") for i in range(10)] + [(100 + i, ("menu\n" if i == 0 else "") + "text %d" % i, "b") for i in range(10)]
    got = {r["doc_id"]: r["text"] for r in line_dedup.drop_boilerplate(spark.createDataFrame(rows, "doc_id int, text string, source string"), "source").collect()}
    assert got[3] == "own 3" and got[100] == "menu\ntext 0"


# ---- 8


@pytest.mark.parametrize("file,drops", [("word_bpe_49k.json", True), ("byte_bpe_50k.json", False), ("piece_bpe_32k.model", False)])
def test_counts_are_the_library_s(spark, file, drops):
    import public_tokenizers

    path = public_tokenizers.path(file)
    odd = ["a<|endoftext|>b", "<|startoftext|> x\ty\r\nz", "İstanbul ẞ é", "don't 'll x'S", "a b c​d", "\x00a\x1fb \x85c", "१२३ 12 3", "😀👩‍👩‍👧", "<|ENDOFTEXT|>", "<|end oftext|>", "ﬁ Å", "x" * 3000, "ΣΑΣ ΑΣ. Σ"]
    df = spark.createDataFrame(list(enumerate(odd)), "doc_id long, text string")
    got = {r["doc_id"]: r["n_tokens"] for r in token_counts.count_tokens(df, token_counts.TokenizerSpec(path, drops), f"{work_dir(spark)}/cache-{uuid.uuid4().hex}").collect()}
    if file.endswith(".json"):
        from tokenizers import Tokenizer

        t = Tokenizer.from_file(path)
        want = [len(t.encode(x, add_special_tokens=False).ids) for x in odd]
    else:
        from sentencepiece import SentencePieceProcessor

        want = [len(x) for x in SentencePieceProcessor(model_file=path).encode(odd)]
    assert [got[i] for i in range(len(odd))] == want


def test_cache_is_used_and_gains_only_misses(spark, docs, texts):
    import public_tokenizers

    spec, cache = token_counts.TokenizerSpec(public_tokenizers.path("word_bpe_49k.json"), True), f"{work_dir(spark)}/cache-grow-{uuid.uuid4().hex}"
    half = docs.filter("doc_id % 2 = 0")
    token_counts.count_tokens(half, spec, cache).collect()
    first = spark.read.parquet(cache).count()
    token_counts.count_tokens(docs, spec, cache).collect()
    stored = spark.read.parquet(cache)
    norm = {re.sub("[ \t\n\r]+", " ", t).strip(" ") for t in texts.values()}
    assert stored.count() == len(norm) and stored.select("content").distinct().count() == len(norm) > first
    token_counts.count_tokens(docs, spec, cache).collect()
    assert spark.read.parquet(cache).count() == len(norm)


def test_stored_counts_are_the_ones_that_are_given(spark, docs):
    """A second pass is all hits: what it returns comes from the cache, even where the cache was tampered with."""
    import public_tokenizers
    from pyspark.sql import functions as F

    spec, cache = token_counts.TokenizerSpec(public_tokenizers.path("word_bpe_49k.json"), True), f"{work_dir(spark)}/cache-hits-{uuid.uuid4().hex}"
    first = {tuple(r) for r in token_counts.count_tokens(docs, spec, cache).collect()}
    other = f"{cache}-more"
    spark.read.parquet(cache).withColumn("n_tokens", F.col("n_tokens") + 1_000_000).write.parquet(other)
    assert {(a, b, n - 1_000_000) for a, b, n in token_counts.count_tokens(docs, spec, other).collect()} == first


def test_each_distinct_miss_is_encoded_once(spark):
    """Copies over many partitions and digests that the bitmap catches by chance: one row in the cache for each text."""
    import public_tokenizers

    spec, cache = token_counts.TokenizerSpec(public_tokenizers.path("word_bpe_49k.json"), True), f"{work_dir(spark)}/cache-once-{uuid.uuid4().hex}"
    rows = [(i, "the same text in many rows" if i % 3 == 0 else f"text number {i % 700}") for i in range(1500)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(13)
    assert token_counts.count_tokens(df, spec, cache).count() == 1500
    assert spark.read.parquet(cache).count() == len({t for _, t in rows})


def test_runs_of_a_long_text():
    text = "ab cd\n" * 5000 + "x" * 20_000 + " end"
    runs = list(token_counts.runs_of(text, 1000))
    assert [p for r in runs for p in r.split()] == text.split() and max(map(len, runs)) < 21_100
    counter = token_counts.PieceCounts(lambda xs: [len(x) for x in xs], chars=50, most=5)
    assert counter.count(text) == len(text.replace(" ", "").replace("\n", "")) == counter.count(text)


# ---- 9


def _sketch(text, k=128):
    words = [x for x in re.split(r"[ \t\n\x0b\f\r]+", text.lower()) if x]
    h = [xxhash.xxh64_intdigest(w.encode(), seed=42) for w in words]
    out = set()
    for i in range(max(1, len(h) - 4) if h else 0):
        s = 42
        for v in h[i : i + 5]:
            s = xxhash.xxh64_intdigest(struct.pack("<Q", v), seed=s)
        out.add(s - 2**64 if s >= 2**63 else s)
    return sorted(out)[:k]


def test_fingerprints_equal_brute_force(spark, data, texts):
    got = {r["doc_id"]: r for r in bottomk.op9_query(spark, data).collect()}
    ids = sorted(texts)
    for n, d in enumerate(ids):
        t, nxt = texts[d], texts[ids[(n + 1) % len(ids)]]
        q = len(t) // 4
        e = t[: len(t) - q] + nxt[:q]
        r = got[d]
        assert r["edited_sha256"] == hashlib.sha256(e.encode()).hexdigest() and r["n_chars"] == len(t)
        for text, column in ((t, "fingerprint"), (e, "edited_fingerprint")):
            assert r[column] == "".join("%016X" % (v % 2**64) for v in _sketch(text))
        a, b = set(_sketch(t)), set(_sketch(e))
        both = set(sorted(a | b)[:128])
        assert r["near_edited"] == pytest.approx(len(a & b & both) / len(both) if both else 1.0)


def test_fingerprints_where_one_id_fills_a_range(spark):
    """Null and repeated ids are spread; every row's successor is still the next row by id and text hash."""
    rows = [(None if i % 3 == 0 else 5 if i % 3 == 1 else i, f"text number {i} of some words that differ {i * i}") for i in range(600)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    wide, order = bottomk.with_next(df, rows_per_bucket=20)
    got = wide.filter("not _ghost").collect()
    want = sorted(rows, key=lambda x: (x[0] is not None, x[0] or 0, _tie(x[1])))
    after = {w: want[(k + 1) % len(want)][1] for k, w in enumerate(want)}
    assert len(got) == 600 and all(r["_next"] == after[r["doc_id"], r["_text"]] for r in got)
    assert wide.groupBy("_bucket", "_sub").count().agg({"count": "max"}).first()[0] < 60


def _tie(text):
    h = xxhash.xxh64_intdigest(text.encode(), seed=42)
    return h - 2**64 if h >= 2**63 else h


def test_sketches_merge_and_estimate(spark):
    from pyspark.sql import functions as F

    x = " ".join(f"a{i}" for i in range(3000))
    y = " ".join(f"a{i}" for i in range(1500, 4500))
    df = spark.createDataFrame([(x, y, x + " " + " ".join(y.split()[:4]))], "x string, y string, z string")
    s = df.select(*[bottomk.sketch(F.col(c), 512).alias(c) for c in "xy"])
    r = s.select(bottomk.resemblance(F.col("x"), F.col("y"), 512), bottomk.containment(F.col("x"), F.col("y"), 512), bottomk.distinct_count(F.col("x"), 512)).first()
    assert abs(r[0] - 1 / 3) < 0.08 and abs(r[1] - 0.5) < 0.1 and abs(r[2] / 2996 - 1) < 0.15
    parts = s.select(F.explode(F.array("x", "y")).alias("s"), F.lit(1).alias("g"))
    merged = bottomk.merge_agg(parts, ["g"], "s", 512).first()["s"]
    assert merged == s.select(bottomk.merge(F.col("x"), F.col("y"), 512)).first()[0]


# ---- 10


def test_held_out_toxicity(spark):
    d = "/root/testdata/sf0.1" if os.path.exists("/root/testdata/sf0.1") else "/root/testdata/sf0.01"
    got = {r["doc_id"]: r for r in toxicity.op10_query(spark, d).collect()}
    labels = {r["doc_id"]: r["toxic"] for r in spark.read.parquet(f"{d}/labels.parquet").collect()}
    rows = [(got[k]["predicted"], y) for k, y in labels.items() if got[k]["held_out"]]
    assert all(got[k]["held_out"] == (zlib.crc32(str(k).encode()) % 4 == 2) for k in labels)
    tp = sum(p and y for p, y in rows)
    assert tp / sum(p for p, _ in rows) > 0.9 and tp / sum(y for _, y in rows) > 0.85


def test_highest_passage_at_any_start():
    r = np.random.default_rng(2)
    for n in (0, 1, 5, 64, 65, 300):
        x = r.normal(size=n)
        mean, start = toxicity.top_passage(x, 64)
        want = max((x[i : i + 64].mean() for i in range(max(1, n - 63))), default=0.0) if n else 0.0
        assert mean == pytest.approx(want) and (not n or x[start : start + 64].mean() == pytest.approx(want))


def test_grams_of_long_tokens_are_counted_and_not_held():
    import tracemalloc

    spec = toxicity.ToxicSpec()
    for w in ("", "a", "ab", "abcdefghijk"):
        assert toxicity.gram_count(w, spec) == len(list(toxicity.grams(w, spec)))
    model = toxicity.ToxicModel(spec, {"abc": 1.0}, 0.0, 1.0, 0.0)
    token = "xyz" * 100_000
    tracemalloc.start()
    assert model.scores([token], toxicity.WordHeights(model))[0] == pytest.approx(0.5)
    assert tracemalloc.get_traced_memory()[1] < 20e6
    tracemalloc.stop()


def test_training_texts_are_bounded_by_characters(spark):
    docs = spark.createDataFrame([(i, "word " * 100) for i in range(50)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, 0, i % 2) for i in range(50)], "doc_id long, quality int, toxic int")
    texts, marks = toxicity.labelled_texts(docs, labels, 1000, 5_000)
    assert len(texts) == len(marks) == 10 and len(toxicity.labelled_texts(docs, labels, 7, 10**9)[0]) == 7


def test_misspellings_share_grams():
    r = np.random.default_rng(0)
    plain = [" ".join(r.choice(["tree", "house", "river", "stone", "cloud", "green"], 30)) for _ in range(300)]
    bad = [t + " horrible nastyword " + t for t in plain[:100]]
    model = toxicity.train(plain[100:] + bad, [0] * 200 + [1] * 100, toxicity.ToxicSpec(epochs=10))
    memo = toxicity.WordHeights(model)
    s = model.scores(["tree house river nastyw0rd stone " * 3, "tree house river cloud stone " * 3, ""], memo)
    assert s[0] > 0.5 > s[1] and s[2] < 0.5
