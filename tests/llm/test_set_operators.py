"""Operators over whole tables: shards, mixes, near-duplicates, neighbours, the pipeline."""

import random
import re
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from privq.llm import mixing, ngram_join, sharding, vector_search


def test_permutation_is_one_and_agrees_with_the_column(spark):
    for n in (1, 2, 3, 10, 97, 1000, 4097):
        placed = [sharding.place(r, n, 7, 5) for r in range(n)]
        assert sorted(slot * 7 + shard for shard, slot in placed) == list(range(n))
        at = spark.range(n).select("id", sharding.permute(F.col("id"), n, 5).alias("at")).collect()
        assert all((r["at"] % 7, r["at"] // 7) == placed[r["id"]] for r in at)


def test_shards(spark):
    rows = [(i, i % 3, "x") for i in range(100)] + [(7, 1, "x")] * 50 + [(None, 1, None)] * 3
    df = spark.createDataFrame(rows, "k long, v long, shard string").withColumnRenamed("shard", "other")
    out = sharding.feistel_shards(df, ["k", "v", "other"], 16)
    found = out.collect()
    sizes = Counter(r["shard"] for r in found)
    assert len(found) == 153 and max(sizes.values()) - min(sizes.values()) <= 1
    for s, n in sizes.items():
        assert sorted(r["slot"] for r in found if r["shard"] == s) == list(range(n))
    again = sharding.feistel_shards(df.repartition(5), ["k", "v", "other"], 16).collect()
    assert sorted(map(str, found)) == sorted(map(str, again))
    assert sharding.feistel_shards(df.limit(0), ["k", "v", "other"], 16).count() == 0


def test_water_filling():
    assert mixing.fill_targets([10, 10, 10], [5, 2, 1], 45) == pytest.approx([20, 50 / 3, 25 / 3])
    out = mixing.fill_targets([1, 1000, 0], [5, 2, 1], 1501.5)
    assert out == pytest.approx([2, 1499.5, 0])
    assert mixing.fill_targets([], [], 0) == []


def test_splitting_tree_is_exact():
    q = mixing.split_quotas([100, 3, 0, 57], 16, 1)
    assert q.sum(axis=0).tolist() == [100, 3, 0, 57] and (q >= 0).all()
    assert q.sum(axis=1).max() - q.sum(axis=1).min() <= 1
    assert (q == mixing.split_quotas([100, 3, 0, 57], 16, 1)).all()


def test_mix(spark):
    g = random.Random(4)
    rows = [(i, "word " * g.randint(0, 60), g.choice(["a", "b", "b", "b", None]), 0) for i in range(2000)] + [(5, "again again", "b", 0)] * 4 + [(9999, None, "a", 0)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, shards int").drop("shards")
    sized = mixing.sizes_of(df)
    planned = mixing.plan_mix(sized, ["doc_id", "size"], shards=4, block_words=2000)
    found = planned.collect()
    assert len(found) == len(rows) and all(0 <= r["times"] <= 2 and len(r["shards"]) == r["times"] for r in found)
    total = defaultdict(int)
    for r in found:
        total[r["source"]] += r["times"] * r["size"]
    for r in found:
        assert abs(total[r["source"]] - r["target"]) <= 60
    assert sum({r["source"]: r["target"] for r in found}.values()) == pytest.approx(1.5 * sum(r["size"] for r in found))
    draws = mixing.draws(planned, ["doc_id"])
    assert draws.count() == sum(r["times"] for r in found)
    again = mixing.plan_mix(sized.repartition(3), ["doc_id", "size"], shards=4, block_words=2000).collect()
    assert sorted(map(str, found)) == sorted(map(str, again))
    assert mixing.plan_mix(sized.limit(0), ["doc_id", "size"]).count() == 0


def test_what_an_edge_block_leaves_is_carried_on(spark):
    rows = [(s * 1000 + i, f"s{s}", 900 if i % 2 else 7) for s in range(12) for i in range(40)] + [(90_000 + i, None, 900 if i % 2 else 7) for i in range(40)]
    df = spark.createDataFrame(rows, "doc_id long, source string, size long")
    found = mixing.plan_mix(df, ["doc_id", "size"], weights=(1.0, 2.0), share=0.7, shards=4, block_words=1000).collect()
    assert len(found) == len(rows)
    for source in {r["source"] for r in found}:
        own = [r for r in found if r["source"] == source]
        over = own[0]["target"] - sum(r["times"] * r["size"] for r in own)
        least = min(r["times"] for r in own)
        assert 0 <= over and all(over < r["size"] for r in own if r["times"] == min(least, 1))
    assert all(len(r["shards"]) == r["times"] and all(0 <= s < 4 for s in r["shards"]) for r in found)


def classes_by_pairs(rows):
    sets = []
    for _, t in rows:
        lowered = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")
        w = re.findall(r"[^\x20\x09-\x0D]+", lowered)
        sets.append({tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set())
    root = list(range(len(rows)))

    def find(k):
        while root[k] != k:
            k = root[k]
        return k

    for a in range(len(rows)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if both and 100 * both >= 80 * (len(sets[a]) + len(sets[b]) - both):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    least = {}
    for k, (i, _) in enumerate(rows):
        least[find(k)] = min(least.get(find(k), i), i)
    return sorted((i, len(sets[k]), least[find(k)]) for k, (i, _) in enumerate(rows))


def near_copies(seed, count):
    g = random.Random(seed)
    vocabulary = ["".join(g.choice("abcdefgh") for _ in range(4)) for _ in range(300)]
    passage = [g.choice(vocabulary) for _ in range(30)]
    texts, base = [], None
    for k in range(count):
        if k % 12 == 0 or base is None:
            base = [g.choice(vocabulary) for _ in range(g.choice([3, 5, 20, 60, 120]))]
        words = list(base)
        for _ in range(g.randint(0, 3)):
            words[g.randrange(len(words))] = g.choice(vocabulary)
        if g.random() < 0.3:
            words = words + passage
        texts.append(g.choice([" ", "\n", "  "]).join(words) if g.random() < 0.9 else " ".join(words).upper())
    return texts + [None, "", " \t", "one", "One", "one two", "ünï ÜNÏ", "a b c d e f", "a b c d e f"]


@pytest.mark.parametrize("hot,block", [(64, 1024), (3, 4)])
def test_join_equals_all_pairs(spark, monkeypatch, hot, block):
    monkeypatch.setattr(ngram_join, "HOT_FROM", hot)
    monkeypatch.setattr(ngram_join, "FIRST_NEAREST", 1)
    monkeypatch.setattr(ngram_join, "MORE_NEAREST", 3)
    monkeypatch.setattr(ngram_join, "BLOCK_ROWS", block)
    rows = list(enumerate(near_copies(11, 260)))
    df = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, node string")
    got = sorted(tuple(r) for r in ngram_join.Join(df).classes().select("doc_id", "n_shingles", "component_id").collect())
    assert got == classes_by_pairs(rows)


@pytest.mark.parametrize(("hot", "block"), [(2, 7), (64, 1024)])
def test_links_inside_a_group_of_near_copies(spark, monkeypatch, hot, block):
    monkeypatch.setattr(ngram_join, "HOT_FROM", hot)
    monkeypatch.setattr(ngram_join, "BLOCK_ROWS", block)
    g, texts = random.Random(21), [None, "", "lone words here"]
    base = [f"w{k}" for k in range(150)]
    for _ in range(150):
        own = list(base)
        for at in g.sample(range(len(own)), g.randint(0, 3)):
            own[at] = g.choice("xyz")
        texts.append(" ".join(own))
    texts += texts[3:8]
    sets = [{tuple(w[k : k + 5]) for k in range(len(w) - 4)} or ({tuple(w)} if w else set()) for w in ((t or "").split() for t in texts)]
    want = [sum(i != j and bool(x) and 100 * len(x & y) >= 80 * len(x | y) for j, y in enumerate(sets)) for i, x in enumerate(sets)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    rows = sorted(tuple(r) for r in ngram_join.Join(df).classes_with_links().collect())
    assert [r[3] for r in rows] == want and max(want) > 100 and len(set(want)) > 5
    assert [r[:3] for r in rows] == sorted(tuple(r) for r in ngram_join.Join(df).classes().collect())


def test_tiles_beyond_the_order_are_split_too(spark, monkeypatch):
    """No shingle is known to be frequent: tile tasks find the large tiles themselves."""
    monkeypatch.setattr(ngram_join, "MOST_ORDERED", 0)
    monkeypatch.setattr(ngram_join, "HOT_FROM", 5)
    monkeypatch.setattr(ngram_join, "BLOCK_ROWS", 6)
    rows = list(enumerate(near_copies(12, 120)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted(tuple(r) for r in ngram_join.Join(df).classes().collect()) == classes_by_pairs(rows)


def test_long_texts_and_slices(monkeypatch):
    """A text beyond a slice, with a word beyond one too, has the same shingles as in one piece."""
    shingler, text = ngram_join.Shingler(), ("Lorem ipsum  dolor\tsit amet " * 300 + "x" * 5000 + " end of it all " * 40).encode()
    whole = shingler.sets_of(np.frombuffer(text, np.uint8))
    monkeypatch.setattr(ngram_join, "SLICE_BYTES", 700)
    pieces = ngram_join.Shingler().sets_of(np.frombuffer(text, np.uint8))
    assert (whole == pieces).all() and len(whole) > 10


def test_long_near_copies_stay_linear(spark):
    """Rows of the common tiles hold a shingle, a set and its size: no more than a fifth of the words each."""
    g = random.Random(3)
    base = [f"w{k}" for k in range(3000)]
    texts = []
    for _ in range(90):
        own = list(base)
        own[g.randrange(3000)] = "other"
        texts.append(" ".join(own))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    join = ngram_join.Join(df)
    _, hot = join.tiles()
    assert hot.count() <= 90 * 601 and set(hot.columns) == {"shingle", "node", "n", "band"}
    assert {r["component_id"] for r in join.classes().collect()} == {0}


def test_join_on_nothing_and_one_of_each(spark):
    df = spark.createDataFrame([(1, "a b c d e f g"), (1, "a b c d e f g"), (2, "a b c d e f g"), (3, None), (4, ""), (5, "other words stand in here now")], "doc_id long, text string")
    assert ngram_join.Join(df.limit(0)).classes().count() == 0
    kept = ngram_join.keep_one_of_each(df).collect()
    assert sorted(r["doc_id"] for r in kept) == [1, 3, 4, 5]


def shuffled_rows(df, column):
    """Rows that the exchanges which carry ``column`` wrote, after ``df`` was collected."""

    def walk(plan):
        kind = plan.getClass().getSimpleName()
        if kind == "AdaptiveSparkPlanExec":
            return walk(plan.executedPlan())
        if kind.endswith("QueryStageExec"):
            return walk(plan.plan())
        own = plan.metrics().apply("shuffleRecordsWritten").value() if kind == "ShuffleExchangeExec" and f"{column}#" in plan.output().mkString(",") else 0
        return own + sum(walk(plan.children().apply(k)) for k in range(plan.children().size()))

    return walk(df._jdf.queryExecution().executedPlan())


@pytest.mark.parametrize("again", [False, True])
def test_texts_that_stay_are_not_shuffled(spark, again):
    """Also where another row repeats an id; rows without shingles all stay then too."""
    g = random.Random(17)
    texts = [" ".join(str(g.randrange(1000)) for _ in range(30)) for _ in range(600)]
    rows = [(k, t, "s") for k, t in enumerate([*texts, *texts[:40], None, "", " "])] + [(641, "", "s"), (None, None, "s"), (None, None, "s")]
    rows += [(5, texts[5], "s")] * 3 * again + [(None, texts[7], "s")] * 2 * again
    df, before = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(3), spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        path = ngram_join.materialize(df, "t")
        kept = ngram_join.keep_one_of_each(path)
        found = [tuple(r) for r in kept.collect()]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    want = [(k, t, "s") for k, t in enumerate(texts)] + [(640, None, "s"), (641, "", "s"), (641, "", "s"), (642, " ", "s"), (None, None, "s"), (None, None, "s")]
    if again:
        want.append((None, texts[7], "s"))  # rows of a repeated id are compared by text
    assert Counter(found) == Counter(want) and kept.columns == df.columns
    assert 40 <= shuffled_rows(kept, "text") < 150


def test_components_of_a_long_chain(spark):
    pairs = [(k, k + 1) for k in range(40)] + [(100, 101)] + [(200, 200 + k) for k in range(1, 30)]
    roots = {r["node"]: r["root"] for r in ngram_join.components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    assert all(roots[k] == 0 for k in range(1, 41)) and roots[101] == 100 and all(roots[200 + k] == 200 for k in range(1, 30))


def test_neighbours_equal_brute_force(spark, monkeypatch):
    monkeypatch.setattr(vector_search, "DATA_BLOCK", 150)
    monkeypatch.setattr(vector_search, "QUERY_BLOCK", 6)
    g = np.random.default_rng(7)
    m = g.normal(size=(700, 24)).astype(np.float32)
    m[100:330] = m[50]  # a third of all rows are one vector
    m[400] = 2 * m[401]
    rows = [(i, [float(x) for x in v]) for i, v in enumerate(m)] + [(700, None), (701, [0.0] * 24), (702, [float("nan")] * 24), (703, [None] * 24), (704, [float("inf")] + [0.0] * 23), (None, [1.0] * 24), (705, [])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    vectors = vector_search.usable(df, "vec_id", "embedding")
    got = defaultdict(list)
    for r in vector_search.nearest(vectors, vectors.where("vec_id % 50 = 0"), 5).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append((r["vec_id"], r["score"]))
    d = m.astype(np.float64)
    for q in range(0, 700, 50):
        s = vector_search.cosine(np.repeat(d[q : q + 1], 700, axis=0), d)
        want = sorted((-x, i) for i, x in enumerate(s.tolist()) if i != q)[:5]
        assert got[q] == [(i, -x) for x, i in want]
    assert set(got) == set(range(0, 700, 50))
    assert vector_search.nearest(vectors.limit(0), vectors.limit(0), 5).count() == 0


def test_pipeline_stages(spark, tmp_path):
    g = random.Random(8)
    plain = ["tree", "house", "green", "walk", "river", "stone", "bread", "cloud", "glass", "paper"]
    rows, labels = [], []
    for i in range(400):
        words = [g.choice(plain) for _ in range(40)]
        y = int(i % 8 == 0)
        if y:
            words[3] = "vileword"
        if i % 10 == 1:
            words[5] = "token=4f3c2b1a0d9e8f7a6b5c4d3e2f1a0b9c8d7e6f5a"
        rows.append((i, " ".join(words), "en", f"s{i % 3}", 1))
        labels.append((i, 1, y))
    rows += [(400 + k, rows[1][1], "en", "s0", 1) for k in range(20)] + [(500, None, None, None, None), (501, "", "en", None, 0)]
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    spark.createDataFrame(rows, schema).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    docs, seen = spark.read.parquet(f"{tmp_path}/documents.parquet"), {}
    for name, stage in corpus_pipeline.STAGES:
        columns = docs.columns
        docs = corpus_pipeline.materialize(stage(spark, docs, str(tmp_path)), "t")
        seen[name] = docs
        if name != corpus_pipeline.STAGES[-1][0]:
            assert docs.columns == columns
    clean = {r[0] for r in rows} - {i for i in range(400) if i % 8 == 0}
    assert {r["doc_id"] for r in seen["toxicity"].collect()} == clean
    one = {r["doc_id"] for r in seen["ngram_jaccard_join"].collect()}
    assert one == clean - set(range(400, 420))
    redacted = {r["doc_id"]: r["text"] for r in seen["secret_scan"].collect()}
    assert set(redacted) == one and all(("[SECRET]" in (redacted[i] or "")) == (i % 10 == 1 and i < 400) for i in one)
    drawn = Counter(r["doc_id"] for r in seen["mixing"].collect())
    assert set(drawn) <= one and max(drawn.values()) <= 2
    assert Counter(r["doc_id"] for r in docs.collect()) == drawn
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == sum(drawn.values())
