"""Worked examples, brute force and properties of the methods."""

import math
from itertools import combinations

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from opatlas.operators import baselines, gmm, itemsets, labelling, pairs, records, score, statements, taxonomy, tfidf, tsne, vectors
from opatlas.sources import parse


def weights(spark, texts, **how):
    df = spark.createDataFrame(list(enumerate(texts)), "stmt_id long, text string")
    got = tfidf.l2(tfidf.weights(tfidf.tokens(df), **how)).collect()
    return {(r.stmt_id, r.term): r.w for r in got}


def test_tfidf_three(spark):
    w = weights(spark, ["clip image", "mask image band", "clip image image"])
    assert w[0, "clip"] == 0 and w[0, "image"] == pytest.approx(-1) and w[2, "image"] == pytest.approx(-1)
    assert w[1, "mask"] == w[1, "band"] == pytest.approx(0.632, abs=1e-3) and w[1, "image"] == pytest.approx(-0.448, abs=1e-3)


def test_tfidf_zero_vectors(spark):
    assert set(weights(spark, ["b", "c c"]).values()) == {0.0}


def test_tfidf_weighted_phrases(spark):
    one = spark.createDataFrame([(0, "a b", 2), (1, "b", 1)], "stmt_id long, text string, n long")
    all_ = spark.createDataFrame([(0, "a b"), (1, "a b"), (2, "b")], "stmt_id long, text string")
    a = {r.term: (r.n_t, r.idf) for r in tfidf.idf(tfidf.tokens(one, weight="n")).collect()}
    assert a == {r.term: (r.n_t, r.idf) for r in tfidf.idf(tfidf.tokens(all_)).collect()}


def test_cosine_matches_brute_force(spark):
    rng = np.random.default_rng(3)
    texts = [" ".join(rng.choice(list("abcdefgh"), rng.integers(1, 6))) for _ in range(40)]
    df = spark.createDataFrame(list(enumerate(texts)), "stmt_id long, text string")
    long = tfidf.l2(tfidf.weights(tfidf.tokens(df), form="smooth"))
    vec = {}
    for r in long.collect():
        vec.setdefault(r.stmt_id, {})[r.term] = r.w
    want = {(a, b) for a, b in combinations(sorted(vec), 2) if sum(vec[a][t] * vec[b].get(t, 0) for t in vec[a]) >= 0.7}
    assert {(r.a, r.b) for r in tfidf.cosine_pairs(long, 0.7).collect()} == want


def nodes(spark, source, lang):
    return parse.to_nodes(spark.createDataFrame([("s", source)], "script_id string, source string"), lang)


@pytest.mark.parametrize("lang", ["js", "py"])
@pytest.mark.parametrize(
    ("source", "nest", "near"),
    [
        ("f(g(x), h(k(y)))\nm(z)", {("f", "g"), ("f", "h"), ("h", "k")}, {("g", "h"), ("f", "m")}),
        ("f(1 + g(x))", {("f", "g")}, set()),
        ("a.b().c()", {("c", "b")}, set()),
    ],
)
def test_trees(spark, lang, source, nest, near):
    n = nodes(spark, source, lang)
    assert {(r.caller, r.callee) for r in pairs.nest(n).collect()} == nest
    assert {(r.caller, r.callee) for r in pairs.next_call(n).collect()} == near


def test_parser_edges(spark):
    n = nodes(spark, "var x = ee.Image('f(g())').map(function(i) { return i.add(1); }); // h(k())\nif (a < b) { print(x ? f(1) : g(2)); } z = (p) => q(p);", "js")
    assert {(r.caller, r.callee) for r in pairs.nest(n).collect()} == {("map", "Image"), ("map", "add"), ("print", "f"), ("print", "g")}
    assert parse.nodes_of("f(", "js") == [] and parse.nodes_of("def", "py") == []
    assert len(parse.nodes_of("(" * 50 + "f(1)" + ")" * 50, "js")) == 2
    assert parse.nodes_of("(" * 100_000, "js") == []
    assert parse.nodes_of("ee.Image(1)", "js", frozenset(["ee"]))[0][5] == "ee.Image"
    checked = parse.check(spark.createDataFrame([("f(1)",), ("f(",), (None,)], "source string"), "js")
    assert [r.parses for r in checked.collect()] == [True, False, True]
    assert parse.strip_code("a('x//y') // c\n/* d */b", "js") == "a('x//y') \nb"


def rec(spark, sets):
    return spark.createDataFrame([(list(s),) for s in sets], "items array<string>")


def test_apriori_five(spark):
    m = itemsets.apriori(rec(spark, ["abc", "ab", "ac", "bc", "abcd"]), "0.4")
    got = {"".join(r["items"]): r.freq for r in m.combos.collect()}
    assert got == {"a": 4, "b": 4, "c": 4, "ab": 3, "ac": 3, "bc": 3, "abc": 2}
    bound = itemsets.apriori(rec(spark, ["abc", "ab", "ac", "bc", "abcd"]), "0.4", support="pair_min")
    assert {"".join(r["items"]): r.freq for r in bound.combos.collect()}["abc"] == 3


def test_boundary_and_empty(spark):
    m = itemsets.apriori(rec(spark, [["x"]] + [["y"]] * 19), "0.05")
    assert {r["items"][0]: r.freq for r in m.combos.collect()} == {"x": 1, "y": 19}
    assert itemsets.least_count("0.05", 20) == 1 and itemsets.least_count("0.05", 21) == 2
    assert itemsets.apriori(rec(spark, []), "0.05").combos.count() == 0



def test_apriori_variants_agree(spark):
    rng = np.random.default_rng(5)
    data = [sorted({str(x) for x in rng.choice(list("abcdefg"), rng.integers(1, 7))}) for _ in range(80)]
    runs = [
        itemsets.apriori(rec(spark, data), "0.1"), itemsets.apriori(rec(spark, data), "0.1", candidates="expand"),
        itemsets.apriori(rec(spark, data), "0.1", strategy="join"), itemsets.apriori(rec(spark, data).repartition(7), "0.1"),
    ]
    got = [{tuple(r["items"]): r.freq for r in m.combos.collect()} for m in runs]
    assert got[0] == got[1] == got[2] == got[3]
    brute = {s: sum(set(s) <= set(d) for d in data) for k in range(1, 8) for s in combinations("abcdefg", k)}
    assert got[0] == {s: n for s, n in brute.items() if n >= 8}
    fp = {tuple(r["items"]): r.freq for r in itemsets.fpgrowth(rec(spark, data), 0.1).collect()}
    assert fp == got[0]
    every = {tuple(r["items"]): r.freq for r in itemsets.enumerate_all(rec(spark, data), 3).collect()}
    assert every == {s: n for s, n in brute.items() if n and len(s) <= 3}
    for s in got[0]:
        for sub in combinations(s, len(s) - 1):
            assert not sub or got[0][sub] >= got[0][s]
    assert runs[1].levels[2].generated >= runs[0].levels[2].counted


def test_truncation_is_told(spark):
    assert itemsets.apriori(rec(spark, ["abcd"] * 5), "0.5", max_k=2).truncated
    assert not itemsets.apriori(rec(spark, ["ab"] * 5), "0.5", max_k=2).truncated


def test_shadow_bound_of_published_sizes():
    sizes = dict(zip(range(1, 11), (51, 322, 850, 1202, 1038, 587, 227, 61, 11, 1), strict=True))
    assert sum(sizes.values()) == 4350 and itemsets.shadow_check(sizes) == []
    assert itemsets.shadow_check({1: 3, 2: 4}) != []


def test_granularity_and_buckets(spark):
    s = spark.createDataFrame([(1, "a b"), (1, "a"), (2, "a b c d e f g h i j")], "script_id long, text string")
    assert {r.bucket: r.n_statements for r in statements.word_buckets(s).collect()} == {"1-5": 2, "10+": 1}
    df = spark.createDataFrame([(1, "One. Two!\n\n"), (2, None), (3, "")], "script_id long, text string")
    assert [(r.script_id, r.pos, r.text) for r in statements.extract(df).orderBy("script_id", "pos").collect()] == [(1, 0, "one"), (1, 1, "two")]
    played = statements.recorded(pd.DataFrame({"script": ["One. Two!\n\n"], "steps": [["First step", "then"]]}))
    assert [r.text for r in statements.extract(df, played).orderBy("pos").collect()] == ["first step", "then"]


def blobs(spark, n=240, seed=1):
    rng = np.random.default_rng(seed)
    c = np.array([[0, 0], [6, 0], [0, 6]])
    x = c[np.arange(n) % 3] + rng.normal(size=(n, 2)) * 0.6
    return spark.createDataFrame(pd.DataFrame({"id": range(n), "x": x[:, 0], "y": x[:, 1], "label": np.arange(n) % 3}))


def test_bic_formula():
    assert gmm.bic(-100, 2, 50) == pytest.approx(243.032, abs=1e-3)
    assert [gmm.n_params(4, c) for c in ("full", "diag", "spherical")] == [23, 19, 15]


def test_mixture_recovers_blobs(spark):
    pts = blobs(spark)
    models = gmm.sweep(pts, [1, 2, 3, 4, 5], max_iter=60)
    curve = gmm.bic_curve(spark, models, 240)
    assert gmm.select_k(curve).first().K == 3
    assert gmm.select_k(curve, "elbow").first().K == 3
    assert models[3].weight.sum() == pytest.approx(1)
    params = spark.createDataFrame(models[3].rows(), gmm.PARAMS)
    got = gmm.assign(pts, params).join(pts, "id").groupBy("k", "label").count().collect()
    assert len(got) == 3
    r = gmm.responsibilities(pts, params).groupBy("id").agg(F.sum("r").alias("s")).agg(F.min("s"), F.max("s")).first()
    assert r[0] == pytest.approx(1) and r[1] == pytest.approx(1)


def test_em_never_falls(spark):
    pts = blobs(spark, 120, 2)
    last = -math.inf
    for steps in range(1, 6):
        m = gmm.sweep(pts, [4], max_iter=steps, tol=-1.0)[4]
        assert m.loglik >= last - 1e-6
        last = m.loglik


def test_perplexity_and_affinities(spark):
    rng = np.random.default_rng(2)
    d2 = np.sort(rng.random((20, 40)) * 5, axis=1)
    p = tsne.widths(d2, 10.0)
    assert np.allclose(p.sum(1), 1) and np.allclose(np.exp(-(p * np.log(p)).sum(1)), 10, rtol=1e-3)
    pts = spark.createDataFrame([(int(i), [float(v) for v in rng.normal(size=3)]) for i in range(30)], "vec_id long, embedding array<double>")
    sym = tsne.symmetrize(tsne.conditional(vectors.neighbours(pts, 8), 4.0), 30).toPandas()
    assert sym["p"].sum() == pytest.approx(1)
    both = {(a, b): p for a, b, p in sym.itertuples(index=False)}
    assert all(both[b, a] == pytest.approx(p) for (a, b), p in both.items())


def test_neighbours_exact_and_bucketed(spark):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(90, 4))
    pts = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "vec_id long, embedding array<double>")
    d = ((x[:, None] - x) ** 2).sum(2)
    np.fill_diagonal(d, np.inf)
    want = {i: set(np.argsort(d[i])[:5].tolist()) for i in range(90)}
    got = vectors.neighbours(pts, 5, block=32).toPandas().groupby("i")["j"].apply(set)
    assert all(got[i] == want[i] for i in range(90))
    near = vectors.neighbours(pts, 5, buckets=3).toPandas().groupby("i")["j"].apply(set)
    assert np.mean([len(near[i] & want[i]) / 5 for i in range(90)]) > 0.8


def test_layouts_keep_blobs_apart(spark):
    rng = np.random.default_rng(6)
    x = np.repeat(np.eye(4)[:3] * 10, 25, axis=0) + rng.normal(size=(75, 4))
    pts = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "vec_id long, embedding array<double>")
    true = vectors.neighbours(pts, 10)
    for method in ("exact", "cells", "landmark"):
        y = tsne.fit(pts, perplexity=8, n_iter=500, method=method, landmarks=60)
        kept = vectors.neighbours(y.select(F.col("id").alias("vec_id"), F.array("x", "y").alias("embedding")), 10).toPandas()
        assert (kept["i"] // 25 == kept["j"] // 25).mean() > 0.9, method
    assert vectors.neighbour_recall(true, true, 10).first()[0] == 1


def test_repulsion_is_close_to_exact():
    y = np.random.default_rng(1).normal(size=(300, 2)) * 5
    d = y[:, None] - y
    w = 1 / (1 + (d**2).sum(2))
    np.fill_diagonal(w, 0)
    force, z = tsne.repulsion(y)
    assert z == pytest.approx(w.sum(), rel=0.01) and np.abs(force - ((w**2)[..., None] * d).sum(1)).max() < 0.05


def test_dbscan_matches_definition(spark):
    pdf = blobs(spark, 150, 3).toPandas()
    pdf.loc[0, ["x", "y"]] = [50.0, 50.0]
    got = baselines.dbscan(spark.createDataFrame(pdf), 0.7, 4).toPandas().set_index("id").sort_index()
    x = pdf[["x", "y"]].to_numpy()
    near = ((x[:, None] - x) ** 2).sum(2) <= 0.49
    core = near.sum(1) >= 4
    assert (got["core"].to_numpy() == core).all()
    root = np.arange(150)
    for _ in range(150):
        for i in np.flatnonzero(core):
            root[i] = root[near[i] & core].min()
    for i in range(150):
        if core[i]:
            assert got["cluster"][i] == root[i]
        elif (near[i] & core).any():
            assert got["cluster"][i] in set(root[near[i] & core])
        else:
            assert got["cluster"][i] == -1


@pytest.fixture()
def shaped(spark):
    """Three stages of groups of 2, 5 / 5, 2, 2 / 3, 1, 1 functions; two groups share a name."""
    sizes = {"s1": {"g": 2, "b": 5}, "s2": {"g": 5, "d": 2, "e": 2}, "s3": {"f": 3, "h": 1, "i": 1}}
    rows, n = [], 0
    for s, groups in sizes.items():
        for g, m in groups.items():
            for k in range(m):
                rows.append((n, s, g, f"{s}{g}{k}"))
                n += 1
    return taxonomy.build(spark.createDataFrame(rows, "l3_id long, l1 string, l2 string, l3 string")).orderBy("l3_id")


def test_structure_scores(spark, shaped):
    rows = shaped.collect()
    assert len(rows) == 21 and {r.n_l3_in_l2 for r in rows} == {1, 2, 3, 5} and {r.m_l2_in_l1 for r in rows} == {2, 3}
    pred = spark.createDataFrame([(i, p) for i, p in enumerate((0, 1, 3, 8, 20, 7, 19, 0))], "item_id long, l3_id long")
    truth = spark.createDataFrame([(i, t) for i, t in enumerate((0, 0, 2, 7, 19, 0, 19, 2))], "item_id long, truth long")
    got = {r.item_id: round(r.structure, 3) for r in score.scored(pred, truth, shaped).collect()}
    # right; right group of 2; of 5; of 5; right stage of 3; same group name in another stage; right; right stage of 2
    assert got == {0: 100, 1: 40, 2: 16, 3: 16, 4: round(20 / 3, 3), 5: 0, 6: 100, 7: 10}


def test_overall_example(spark):
    df = spark.createDataFrame([(False, True, True, 5, 2)], "t3 boolean, t2 boolean, t1 boolean, n int, m int")
    r = df.select(score.structure().alias("s"), score.semantic(F.lit(0.5)).alias("e")).select("s", "e", score.overall(F.col("e"), F.col("s")).alias("o")).first()
    assert (r.s, r.e) == (16, 50) and r.o == pytest.approx(36.4)


def ballots(spark, rows):
    return spark.createDataFrame(rows, "item_id long, model string, run int, l3_id long")


def test_vote_ties_and_invariants(spark):
    b = ballots(spark, [(1, "M2", 1, 5), (1, "M3", 1, 9), (2, "M1", 1, 7), (2, "M1", 2, 4), (3, "M4", 1, None)])
    t = labelling.tallies(b)
    votes = {(r.subset, r.item_id): r.l3_id for r in labelling.pooled(t).collect()}
    assert votes["M2+M3", 1] == 9  # M3 goes before M2
    assert votes["M1", 2] == 4  # the lower id
    assert (("M4", 3) in votes) is False
    alone = {(r.model, r.item_id): r.l3_id for r in labelling.single(t).collect()}
    assert all(votes[m, i] == v for (m, i), v in alone.items())
    again = {(r.subset, r.item_id): r.l3_id for r in labelling.pooled(labelling.tallies(b.repartition(9))).collect()}
    assert again == votes and len(labelling.subsets()) == 15


def test_more_models_help_simulated_annotators(spark, shaped):
    items = spark.createDataFrame([(i, i % 21) for i in range(120)], "item_id long, truth long")
    res = labelling.resolve(labelling.run(items, lambda x: labelling.seeded(x, shaped)), shaped)
    s = score.report(score.scored(labelling.pooled(labelling.tallies(res)), items, shaped)).toPandas().set_index("subset")
    assert len(s) == 15 and s["overall"]["M1+M2+M3+M4"] >= s[s["n_models"] == 1]["overall"].mean()
    assert s["overall"].between(0, 100).all()


def test_fuzzy_finds_itself(spark, shaped):
    names = shaped.select(F.col("l3").alias("raw_label"), F.col("l3_id").alias("want"))
    for how in ("edit", "dice", "cosine"):
        got = labelling.fuzzy(names, shaped, how).join(names, "raw_label")
        assert got.where("l3_id <> want").count() == 0, how


def test_fuzzy_compares_with_all_functions_of_a_large_taxonomy(spark):
    names = [f"fn {i:05d}" for i in range(5_200)] + ["zq"]
    tax = spark.createDataFrame(list(enumerate(names)), "l3_id long, l3 string")
    asked = ["qz", "fn 00017x", "zzq"]  # the first shares no pair of characters with any function

    def edit(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            last, row = row, [i]
            for j, y in enumerate(b, 1):
                row.append(min(last[j] + 1, row[-1] + 1, last[j - 1] + (x != y)))
        return row[-1]

    got = {r.raw_label: r for r in labelling.fuzzy(spark.createDataFrame([(x,) for x in asked], "raw_label string"), tax).collect()}
    for x in asked:
        sims = [1 - edit(x, y) / max(len(x), len(y)) for y in names]
        best = max(range(len(names)), key=lambda i: (round(sims[i], 9), -i))
        assert got[x].l3_id == best and abs(got[x].sim - sims[best]) < 1e-9


def test_providers_by_words(spark):
    tax = spark.createDataFrame([(1, "clean", "mask", "cloud mask"), (2, "clean", "clip", "clip image"), (3, "show", "map", "add layer")], "l3_id long, l1 string, l2 string, l3 string")
    items = spark.createDataFrame([(1, "mask the cloud"), (2, "add a layer to the map"), (3, "nothing alike"), (4, None)], "item_id long, text string")
    for provider in (labelling.lexical, labelling.narrowing):
        got = {r.item_id: r.raw_label for r in labelling.run(items, lambda i, p=provider: p(i, tax)).collect()}
        assert got == {1: "cloud mask", 2: "add layer"}


def test_recorded_and_bad_providers(spark):
    items = spark.createDataFrame([(1,)], "item_id long")
    replies = spark.createDataFrame([(1, "A", 1, "x"), (1, "A", 1, "x"), (2, "A", 1, "y")], "item_id long, model string, run int, raw_label string")
    assert labelling.run(items, lambda i: labelling.recorded(i, replies)).count() == 1
    with pytest.raises(ValueError, match="raw_label"):
        labelling.run(items, lambda i: i)


def test_sampling_quota(spark):
    sizes = (51, 322, 850, 1202, 1038, 587, 227, 61, 11, 1)
    rows = [(n, k) for k, m in enumerate(sizes, 1) for n in range(m)]
    q = score.strata(spark.createDataFrame(rows, "combo_id long, k int")).toPandas()
    assert q["quota"].sum() == 150 and (q["quota"] <= q["size"]).all()


def test_decisions(spark):
    d = spark.createDataFrame([(1, "keep", None, "a", "b", "c"), (2, "merge", 1, None, None, None), (3, "drop", None, None, None, None)], "cluster_id int, action string, merge_into int, l1 string, l2 string, l3 string")
    got = taxonomy.apply_decisions(spark.createDataFrame([(1,), (2,), (3,)], "cluster int"), d).orderBy("cluster").collect()
    assert [(r.cluster, r.target, r.l3) for r in got] == [(1, 1, "c"), (2, 1, "c")]


def test_records_units(spark):
    p = spark.createDataFrame([("r", "a", "b"), ("r", "a", "c"), ("s", "a", "b"), ("s", "b", "b")], "rec_id string, caller string, callee string")
    assert {r.rec_id: r["items"] for r in records.make(p, "caller").collect()} == {"a": ["b", "c"], "b": ["b"]}
    assert sorted(tuple(r["items"]) for r in records.make(p, "pair").collect()) == [("a", "b"), ("a", "b"), ("a", "c"), ("b",)]
    w = records.compress(records.make(p, "pair"))
    assert w.agg(F.sum("w")).first()[0] == 4 and w.count() == 3


def test_wrong_labels_are_drawn_by_place(spark):
    """No row carries a list of functions, and labels are those of lists made here, names repeated or not."""
    import hashlib

    def noise(*parts):
        return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:8], 16) / 2**32

    tax = [(3 * n, f"s{n % 3}", f"g{n % 7 % 2}", f"Name#{n % 50:03d}") for n in range(80)]
    items = [(f"i{n}", 3 * (n % 80)) for n in range(120)]
    got = labelling.seeded(spark.createDataFrame(items, "item_id string, truth long"), spark.createDataFrame(tax, "l3_id long, l1 string, l2 string, l3 string"))
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert "collect_list(l3_id" not in plan
    by_id, want = {t[0]: t for t in tax}, set()
    for item, truth in items:
        _, l1, l2, own = by_id[truth]
        for m in labelling.MODELS:
            for r in range(1, labelling.RUNS + 1):
                name = own
                if 0.4 * noise(item, "d") + 0.3 * noise(item, m) + 0.3 * noise(item, m, r) < labelling.ERROR[m]:
                    where = noise(item, m, r, "where")
                    pool = [t[3] for t in tax if where >= 0.8 or t[1] == l1 and (where >= 0.5 or t[2] == l2)]
                    name = pool[int(noise(item, m, r, "pick") * len(pool))]
                if noise(item, m, r, "spell") < 0.1:
                    name = name[:3].lower() + name[4:]
                want.add((item, m, r, name))
    rows = [tuple(x) for x in got.select("item_id", "model", "run", "raw_label").collect()]
    assert len(rows) == len(want) and set(rows) == want


def test_names_that_repeat_are_compared_once(spark):
    tax = spark.createDataFrame([(9, "Alpha"), (4, "Alpha"), (5, "Beta")], "l3_id long, l3 string")
    lost = spark.createDataFrame([("alha",), ("beta",)], "raw_label string")
    got = {r.raw_label: r.l3_id for r in labelling.fuzzy(lost, tax).collect()}
    assert got == {"alha": 4, "beta": 5}


def test_all_pairs_stay_off_spark_and_in_blocks(spark, monkeypatch):
    rng = np.random.default_rng(5)
    monkeypatch.setattr(tsne, "BLOCK", 16)
    x = rng.normal(size=(50, 3))
    pts = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "vec_id long, embedding array<double>")
    p = tsne.exact_affinities(x, 6.0)
    want = tsne.symmetrize(tsne.conditional(vectors.neighbours(pts, 49), 6.0), 50).toPandas()
    assert np.allclose(p[want["i"], want["j"]], want["p"], atol=1e-6) and p.sum() == pytest.approx(1) and not p.diagonal().any()
    y = rng.normal(size=(50, 2))
    w = 1 / (1 + ((y[:, None] - y) ** 2).sum(2))
    np.fill_diagonal(w, 0)
    m = (2 * p - w / w.sum()) * w
    assert np.allclose(tsne.exact_gradient(p)(y, 2.0), 4 * (m.sum(1)[:, None] * y - m @ y))

    def refuse(*a, **k):
        raise AssertionError("all pairs of points as rows")

    monkeypatch.setattr(tsne, "neighbours", refuse)
    assert tsne.fit(pts, 6.0, 20, method="landmark", landmarks=40).count() == 50
    assert tsne.fit(pts.limit(1), 6.0, 20, method="exact").count() == 1


def test_summed_weights_move_no_statement(spark):
    texts = [(0, "a b b"), (0, "a c"), (1, "b c c d"), (1, "d"), (None, "a"), (1, "")]
    s = spark.createDataFrame([(str(i), c, t) for i, (c, t) in enumerate(texts)], "stmt_id string, cluster long, text string")
    tok = tfidf.tokens(s).join(s.select("stmt_id", "cluster"), "stmt_id")
    long = tfidf.weights(tfidf.tokens(s)).join(s, "stmt_id").groupBy("cluster", "term").agg(F.sum("w").alias("w"))
    of = lambda df: {(r.cluster, r.term): r.w for r in df.collect()}
    got, want = of(tfidf.summed(tok, "cluster")), of(long)
    assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k]) for k in want)


def test_kernel_totals_of_blocks(spark):
    """The sums that symmetric affinities of some points need are those over all pairs, whatever the blocks."""
    rng = np.random.default_rng(3)
    rows = [(i, [float(x) for x in rng.normal(size=5)], i % 3) for i in range(90)] + [(7, [0.5] * 5, 1), (90, [1.0] * 5, 3), (91, None, 0), (92, [1.0] * 5, None)]
    points = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    known = [(i, np.array(v, np.float32).astype(float), c) for i, v, c in rows if v is not None and c is not None]
    want = {}
    for i, v, c in known:
        want[i] = want.get(i, 0.0) + sum(float(np.exp(-((v - w) ** 2).sum() / 8)) for j, w, d in known if c == d and i != j)
    for block in (4, 1000):
        got = {r.i: r.t for r in tsne.kernel_totals(points, 2.0, block=block).collect()}
        assert got == pytest.approx(want)


def test_symmetric_affinities_of_some_points(spark):
    rng = np.random.default_rng(4)
    pts = spark.createDataFrame([(i, [float(x) for x in rng.normal(size=4)], 0) for i in range(40)], "vec_id long, embedding array<double>, label int")
    near = vectors.neighbours(pts, 39)
    whole = {(r.i, r.j): r.p for r in tsne.symmetrize(tsne.conditional_fixed(near, 1.5), 40).collect()}
    got = {(r.i, r.j): r.p for r in tsne.symmetric_fixed(near.where("i % 10 = 0"), tsne.kernel_totals(pts, 1.5, block=9), 40, 1.5).collect()}
    assert got == pytest.approx({k: p for k, p in whole.items() if k[0] % 10 == 0})


def test_symmetric_affinities_of_all_points(spark):
    """Blocks give what rows of all pairs give, with repeated ids, an id in two groups, and vectors that lack values."""
    rng = np.random.default_rng(5)
    rows = [(i, [float(x) for x in rng.normal(size=4)], i % 2) for i in range(60)] + [(7, [0.5] * 4, 1), (8, [0.1] * 4, 1), (60, None, 0), (61, [None, 1.0, 0.0, 0.0], 1)]
    rows += [(62, [1.0] * 4, None), (None, [1.0] * 4, 0), (63, [1.0] * 4, 3), (64, [0.5, 0.5], 0)]
    points = lambda r: spark.createDataFrame(r, "vec_id long, embedding array<float>, label int")

    def want(rows):
        near = []
        for i, v, c in rows:
            for j, w, d in rows:
                if None not in (i, j, c, d) and i != j and c == d:
                    both = [(x - y) ** 2 for x, y in zip(np.array(v or [], np.float32).astype(float), np.array(w or [], np.float32).astype(float)) if not np.isnan(x - y)]
                    near.append((i, j, float(sum(both)) if both else None))
        near = spark.createDataFrame(near, "i long, j long, d2 double")
        return {(r.i, r.j): r.p for r in tsne.symmetrize(tsne.conditional_fixed(near, 1.5), len(rows)).collect()}

    for part in (rows, rows[:60]):
        known = want(part)
        for block in (7, 1000):
            got = tsne.symmetric_whole(points(part), 1.5, block=block).collect()
            assert len(got) == len(known) and {(r.i, r.j) for r in got} == set(known)
            assert all(r.p == (None if known[r.i, r.j] is None else pytest.approx(known[r.i, r.j])) for r in got)
    assert tsne.symmetric_whole(points([]), 1.5).count() == 0


def test_fuzzy_deals_few_labels_over_tasks_and_sorts_no_pair(spark):
    tax = spark.createDataFrame([(3 * i + 7, f"fn {i:04d}") for i in range(300)], "l3_id long, l3 string")
    lost = spark.createDataFrame([("fn 01x7",), ("FN 0042",), (None,)], "raw_label string")
    for how in ("edit", "jaccard"):
        got = labelling.fuzzy(lost, tax, how)
        plan = got._jdf.queryExecution().executedPlan().toString()
        assert "SortAggregate" not in plan[: plan.index("REPARTITION_BY_NUM")], how
        rows = {r.raw_label: (r.l3_id, r.sim) for r in got.collect()}
        assert rows[None] == (7, None) and rows["FN 0042"][0] == 3 * 42 + 7
        assert rows["fn 01x7"][0] == (3 * 107 + 7 if how == "edit" else 7)


def test_edits_of_words_and_cells_agree_with_spark(spark):
    from opatlas.functions.edits import Names
    from opatlas.functions.text import edit_ratio

    rng = np.random.default_rng(3)
    word = lambda n: "".join(rng.choice(list("abß語😀 "), n))
    names = ["", *(word(n) for n in (1, 2, 5, 5, 9, 63, 64, 65, 70, 130) for _ in range(4))]
    asked = ["", "zz", *(word(n) for n in (1, 5, 8, 63, 64, 65, 90)), names[30][:60] + "x", names[40] + "y"]
    pairs = spark.createDataFrame([(a, i, b) for a in asked for i, b in enumerate(names)], "a string, i int, b string")
    rows = pairs.select("a", "i", edit_ratio(F.col("a"), F.col("b")).alias("s")).collect()
    index = Names(names)
    for a in asked:
        want = min((-round(r.s, 9), r.i) for r in rows if r.a == a)
        place, sim = index.nearest(a)
        assert (-round(sim, 9), place) == want, a
