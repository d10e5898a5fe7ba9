"""The exact near-duplicate join against comparing all with all."""

import numpy as np
import pytest

from mixwright.operators import corpus
from mixwright.operators.components import components
from mixwright.operators.near import NearSets


def rows(df):
    return sorted(df.select("doc_id", "text").collect())


def brute_classes(docs, width=5, threshold=0.8):
    """Least id of each document's class, and the pairs of distinct sets, by comparing all with all."""
    sets = {}
    for d, t in docs:
        w = (t or "").lower().encode().split()
        sets[d] = frozenset(zip(*(w[i:] for i in range(width)))) if len(w) >= width else frozenset([tuple(w)])
    boss = {d: d for d in sets}

    def top(x):
        while boss[x] != x:
            x = boss[x]
        return x

    pairs = set()
    for a in sets:
        for b in sets:
            if a < b and len(sets[a] & sets[b]) >= threshold * len(sets[a] | sets[b]):
                pairs.add((a, b))
                x, y = sorted((top(a), top(b)))
                boss[y] = x
    return {d: top(d) for d in sets}, pairs


def planted(spark, seed=5):
    """Copies with so many words changed that similarities lie between 0.6 and 0.98, a common passage, and short texts."""
    rng = np.random.default_rng(seed)
    word = lambda: f"w{rng.integers(5000)}"
    texts, common = [None, "", "one two", "ONE two", "one two three", "a b c d", "a b c d e"], [word() for _ in range(60)]
    for i in range(12):
        base = [word() for _ in range(150)] if i else common + [word() for _ in range(5)]
        texts.append(" ".join(base))
        for k in range(1, 7 if i else 40):
            near = list(base)
            for at in rng.choice(len(near), 1 + k % 7 if i else 1 + k % 3, replace=False):
                near[at] = word()
            texts.append(" ".join(near))
    texts += [" ".join(common + [word() for _ in range(40)]) for _ in range(25)]
    return spark.createDataFrame([(int(i), t) for i, t in enumerate(texts)], "doc_id long, text string").repartition(3)


@pytest.mark.parametrize("bucket,chunk", [(2, 4), (16, 1000)])
def test_classes_equal_brute_force(spark, bucket, chunk):
    docs = planted(spark)
    near = NearSets(docs, shard_bytes=20_000)
    assert {r.id: r.component for r in near.classes(near.links(bucket_rows=bucket, chunk_rows=chunk)).collect()} == brute_classes(rows(docs))[0]


@pytest.mark.parametrize("bucket,chunk", [(2, 4)])
def test_every_pair_is_found(spark, bucket, chunk):
    docs = planted(spark, 6)
    near = NearSets(docs)
    names = dict(near.nodes.select("node", "least").collect())
    got = {tuple(sorted((names[r.a], names[r.b]))) for r in near.links(every=True, bucket_rows=bucket, chunk_rows=chunk).collect()}
    first = {}
    for d, t in rows(docs):
        w = (t or "").lower().split()
        first.setdefault(frozenset(zip(*(w[i:] for i in range(5)))) if len(w) >= 5 else frozenset([tuple(w)]), d)
    assert got == {(a, b) for a, b in brute_classes(rows(docs))[1] if a in first.values() and b in first.values()}


def test_known_links_change_no_class(spark):
    docs = planted(spark)
    near = NearSets(docs, mark=lambda s: len(s))
    first = near.links()
    label = first.selectExpr("b node", "a label").unionByName(first.selectExpr("a node", "a label")).groupBy("node").agg({"label": "min"}).withColumnRenamed("min(label)", "label")
    more = near.links(known=label, bucket_rows=2)
    assert {r.id: r.component for r in near.classes(first.unionByName(more)).collect()} == brute_classes(rows(docs))[0]
    assert near.nodes.filter("mark <> n").count() == 0


def test_near_pairs_and_members(spark):
    docs = planted(spark)
    docs = docs.unionByName(docs.selectExpr("doc_id + 1000 as doc_id", "text"))
    least, pairs = brute_classes(rows(docs))
    got = {r.doc_id: (r.representative, r.class_id) for r in corpus.near_members(docs).collect()}
    assert {d: c for d, (_, c) in got.items()} == least
    same = {d: p for d, (p, _) in got.items()}
    assert all(same[d + 1000] == same[d] for d in same if d < 1000) and same[3] == 2
    want = {(min(x), max(x)) for x in ((same[a], same[b]) for a, b in pairs) if x[0] != x[1]}
    assert {(r.id_a, r.id_b) for r in corpus.near_pairs(docs).collect()} == want
    assert {r.doc_id for r in corpus.near_dedup(docs).collect()} == set(least.values())


def test_edge_cases(spark):
    docs = spark.createDataFrame([(None, "a b c d e f"), (1, "a b c d e f"), (1, "other words here"), (2, "other words here"), (3, None), (4, " ")], "doc_id long, text string")
    near = NearSets(docs)
    assert sorted(((r.id, r.component) for r in near.classes(near.links()).collect()), key=str) == sorted([(None, None), (1, 1), (1, 1), (2, 1), (3, 3), (4, 3)], key=str)
    none = NearSets(docs.filter("doc_id > 9"))
    assert none.classes(none.links()).count() == 0
    with pytest.raises(TypeError, match="integers"):
        NearSets(docs.selectExpr("cast(doc_id as string) doc_id", "text"))


def test_components_of_a_long_chain(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(60)] + [(100, 101)], "a long, b long")
    assert dict(components(edges).collect()) == {**{i: 0 for i in range(1, 61)}, 101: 100}
