"""Stage A as a chain, and its parts against brute force and planted structure."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from opatlas.operators import cluster_eval, framework, gmm, prompts, taxonomy, tfidf, tsne, vectors

TOPICS = {
    "cloud": "mask cloud shadow pixel cirrus haze", "water": "river lake shore flood wet depth", "fire": "burn scar ash flame heat smoke",
    "crop": "wheat maize field yield harvest soil", "city": "road roof street building block night",
}


@pytest.fixture(scope="module")
def statements(spark):
    rng = random.Random(2)
    rows = []
    for topic, words in TOPICS.items():
        for i in range(60):
            text = " ".join([topic, *rng.sample(words.split(), 3)])
            rows += [(text, f"src{rng.randrange(6)}")] * rng.randint(1, 3)
    # one cluster that stands in one source only
    rows += [(" ".join(["sensor", *rng.sample("alpha beta gamma delta epsilon".split(), 2)]), "src0") for _ in range(60)]
    return spark.createDataFrame(rows, "text string, source string")


@pytest.fixture(scope="module")
def built(statements):
    return framework.build(statements, min_df=1, most_k=12, landmarks=400, n_iter=400, perplexity=10.0)


def test_rows_equal_the_long_form(spark, statements):
    tok = tfidf.tokens(framework.distinct(statements), weight="w")
    terms = tfidf.idf(tok)
    joined = tfidf.tf(tok).join(terms, "term").select("stmt_id", "term", (F.col("tf") * F.col("idf")).alias("w"))
    for got, want in ((tfidf.weights(tok), joined), (tfidf.normed(tok), tfidf.l2(joined))):
        a, b = ({(r.stmt_id, r.term): r.w for r in df.collect()} for df in (got, want))
        assert set(a) == set(b) and all(a[k] == pytest.approx(b[k], abs=1e-12) for k in a)
    assert tfidf.rows(tok, terms, most=3) is None
    odd = spark.createDataFrame([(1, []), (2, None), (3, ["none"]), (4, ["cloud", "none", "cloud"])], "stmt_id long, tok array<string>").withColumn("w", F.lit(1))
    got = {r.stmt_id: (list(r.terms), list(r.w)) for r in tfidf.rows(odd, terms, normed=False).collect()}
    idf = {r.term: r.idf for r in terms.collect()}["cloud"]
    assert got[1] == got[2] == got[3] == ([], []) and got[4][0] == ["cloud"] and got[4][1][0] == pytest.approx(2 / 3 * idf)


def test_mllib_gives_the_smooth_form(spark, statements):
    """MLlib's idf of the same texts equals ln((N + 1) / (n + 1)); its vectors have the same entries."""
    from pyspark.ml.functions import vector_to_array

    s = framework.distinct(statements)
    model = tfidf.mllib_pipeline(s)
    words = model.stages[1].vocabulary
    made = model.transform(s).select("stmt_id", vector_to_array("features").alias("v")).limit(50).collect()
    ours = {}
    for r in tfidf.normed(tfidf.tokens(s), form="smooth").collect():
        ours.setdefault(r.stmt_id, {})[r.term] = r.w
    for r in made:
        assert {words[i]: x for i, x in enumerate(r.v) if x} == pytest.approx(ours[r.stmt_id], abs=1e-9)


def test_folding_keeps_inner_products(spark, statements):
    sparse = tfidf.rows(tok := tfidf.tokens(framework.distinct(statements)), tfidf.idf(tok))
    vec = {r.stmt_id: dict(zip(r.terms, r.w, strict=True)) for r in sparse.collect()}
    flat = {r.vec_id: np.array(r.embedding) for r in framework.fold(sparse, 256).collect()}
    assert set(vec) == set(flat)
    ids = random.Random(1).sample(sorted(vec), 40)
    gaps = [sum(w * vec[b].get(t, 0) for t, w in vec[a].items()) - flat[a] @ flat[b] for a in ids for b in ids]
    assert np.abs(gaps).mean() < 0.05


def test_expectation_equals_the_densities():
    rng = np.random.default_rng(4)
    x, w = rng.normal(size=(500, 2)) * 30, rng.integers(1, 5, 500).astype(float)
    m = gmm.start(x, 7)
    parts = m.log_parts(x)
    top = parts.max(1, keepdims=True)
    e = np.exp(parts - top)
    ll, sums = gmm.expect(m, gmm.features(x), w)
    assert ll == pytest.approx(float((w * (top[:, 0] + np.log(e.sum(1)))).sum()), rel=1e-9)
    assert np.allclose(sums, (e / e.sum(1, keepdims=True) * w[:, None]).T @ gmm.features(x))


def test_both_ways_to_sweep_agree(spark):
    rng = np.random.default_rng(5)
    xy = np.concatenate([rng.normal(c, 0.3, (60, 2)) for c in ((0, 0), (4, 0), (0, 4))])
    points = spark.createDataFrame([(i, float(a), float(b), i % 3 + 1) for i, (a, b) in enumerate(xy)], "id long, x double, y double, w int")
    a, b = (gmm.sweep(points, [1, 3, 6], weight="w", strategy=s) for s in ("by_model", "by_points"))
    for k in (1, 3, 6):
        assert a[k].loglik == pytest.approx(b[k].loglik, rel=1e-9) and a[k].steps == b[k].steps
        assert np.allclose(a[k].mean, b[k].mean, atol=1e-6)
    total = float(sum(i % 3 + 1 for i in range(180)))
    assert min((1, 3, 6), key=lambda k: gmm.bic(a[k].loglik, k, total)) == 3


def test_grid_of_k():
    ks = gmm.grid(500)
    assert ks[:16] == list(range(1, 17)) and ks[-1] == 500 and ks == sorted(set(ks)) and all(b / a <= 1.13 for a, b in zip(ks[16:], ks[17:], strict=False))
    assert gmm.grid(3) == [1, 2, 3] and gmm.grid(0) == []


def test_chain_finds_the_topics(built, statements):
    """Clusters follow the planted topics, the cluster of one source is dropped, and the levels nest."""
    topic = {r.stmt_id: r.text.split()[0] for r in built.phrases.collect()}
    rows = [(topic[r.stmt_id], r.cluster) for r in built.assigned.collect()]
    assert len(rows) == len(topic) == statements.select("text").distinct().count()
    main = {c: max((t for t, x in rows if x == c), key=[t for t, x in rows if x == c].count) for c in {c for _, c in rows}}
    assert sum(main[c] == t for t, c in rows) >= 0.95 * len(rows)
    assert 5 <= built.chosen["argmin"] <= 12
    decided = {r.cluster: r for r in built.decisions.collect()}
    assert set(decided) == set(main)
    assert all((decided[c].action == "drop") == (main[c] == "sensor") for c in main)
    functions = built.functions.collect()
    assert {r.l3_id for r in functions} == {r.target for r in decided.values() if r.target is not None}
    groups = {(r.l1, r.l2) for r in functions}
    assert len({l2 for _, l2 in groups}) == len(groups) and all(r.n_l3_in_l2 == sum((x.l1, x.l2) == (r.l1, r.l2) for x in functions) for r in functions)
    terms = {(r.cluster, r.term) for r in built.terms.collect()}
    assert sum((c, main[c]) in terms for c in main) >= 0.8 * len(main)


def test_chain_measures(built):
    got = {r.measure: r.value for r in framework.quality(built, 5, 100).collect()}
    assert got["neighbour_recall"] > 0.2 and -0.1 < got["ari_with_source"] < 0.5
    assert sum(r.w for r in built.layout.collect()) == sum(r.w for r in built.phrases.collect())


def test_layouts_keep_neighbours(spark):
    """Each method on one table: recall of ten neighbours, trust, and the labels found again."""
    rng = np.random.default_rng(6)
    data = np.concatenate([rng.normal(c, 1.0, (60, 8)) for c in np.eye(8)[:4] * 12])
    points = spark.createDataFrame([(i, x.tolist(), i // 60) for i, x in enumerate(data)], "vec_id long, embedding array<double>, label int")
    every = vectors.neighbours(points, 239)
    for method, least in (("exact", 0.5), ("cells", 0.5), ("landmark", 0.3)):
        laid = tsne.fit(points, perplexity=15.0, n_iter=400, method=method, landmarks=120)
        kept = vectors.neighbours(laid.select("id", F.array("x", "y").alias("v")), 10, "v", "id")
        assert vectors.neighbour_recall(every, kept, 10).first()["recall"] > least, method
        assert vectors.trust(every, kept, 10, 240).first()["trustworthiness"] > 0.85, method


def test_nearest_equals_all_pairs(spark):
    x = np.random.default_rng(7).normal(size=(90, 5))
    points = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>").repartition(4)
    got = {(r.i, r["rank"]): r.j for r in vectors.nearest(points.where("vec_id < 20"), points, 7).collect()}
    d = ((x[:, None] - x[None]) ** 2).sum(-1)
    np.fill_diagonal(d, np.inf)
    assert got == {(i, r + 1): int(j) for i in range(20) for r, j in enumerate(np.argsort(d[i])[:7])}
    with pytest.raises(ValueError, match="asked"):
        vectors.nearest(points, points, 3, limit=10)


def test_pairs_of_too_many_points_are_refused(spark):
    points = spark.range(tsne.EXACT_POINTS + 1).select("id", F.rand(1).alias("x"), F.rand(2).alias("y"))
    with pytest.raises(ValueError, match="too many pairs"):
        tsne.q(points)


def test_pca_finds_the_axes(spark):
    rng = np.random.default_rng(8)
    x = rng.normal(size=(300, 6)) * (9, 4, 1, 0.5, 0.2, 0.1)
    got = vectors.pca2(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")).orderBy("id").toPandas()
    centred = x - x.mean(0)
    _, _, axes = np.linalg.svd(centred, full_matrices=False)
    for col, axis in (("x", axes[0]), ("y", axes[1])):
        want = centred @ axis
        assert np.allclose(np.abs(got[col]), np.abs(want), atol=1e-8)


def test_silhouette_by_hand(spark):
    points = [(0.0, 0), (1.0, 0), (10.0, 1), (12.0, 1)]
    df = spark.createDataFrame([([x], c) for x, c in points], "embedding array<double>, label int")
    values = []
    for i, (x, c) in enumerate(points):
        mean = lambda k: np.mean([(x - y) ** 2 for j, (y, d) in enumerate(points) if d == k and j != i])  # noqa: B023, E731
        a, b = mean(c), mean(1 - c)
        values.append((b - a) / max(a, b))
    assert cluster_eval.silhouette(df) == pytest.approx(np.mean(values), abs=1e-6)


def test_merging_similar_clusters(spark):
    rows = [(1, "a", 1.0), (1, "b", 1.0), (2, "a", 1.0), (2, "b", 0.9), (3, "c", 1.0), (4, "b", 1.0), (4, "c", 0.0), (5, "d", 0.0)]
    cent = spark.createDataFrame(rows, "cluster long, term string, w double")
    assert {r.cluster: r.merged for r in taxonomy.merge_similar(cent, 0.9).collect()} == {1: 1, 2: 1, 3: 3, 4: 4, 5: 5}
    assert {r.cluster: r.merged for r in taxonomy.merge_similar(cent, 0.6).collect()}[4] == 1


def test_replies(spark):
    good = '{"overall": "all", "steps": [{"pos": 1, "name": "a", "description": "x"}, {"pos": 2, "name": "b", "description": null}]}'
    df = spark.createDataFrame([(1, good), (2, good[:30]), (3, None), (4, '{"overall": "none"}'), (5, '{"overall": "o", "steps": []}')], "script_id long, reply string")
    steps, broken = prompts.parse_reply(df)
    assert [tuple(r) for r in steps.orderBy("pos").collect()] == [(1, "all", 1, "a", "x"), (1, "all", 2, "b", None)]
    assert sorted(r.script_id for r in broken.collect()) == [2, 3, 4]


def test_criterion_by_hand():
    assert gmm.bic(-100, 2, 50) == pytest.approx(200 + 11 * math.log(50))
