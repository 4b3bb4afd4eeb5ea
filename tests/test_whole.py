"""Queries over whole tables against counts that share nothing with their SQL."""

import os
from itertools import combinations

import pytest

from opatlas.operators import itemsets, records
from opatlas.queries import catalogs
from opatlas.sources import corpus

SF = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")
RUNS = {n: f for c in catalogs() for n, f in c.runs.items()}


def mixed_by_fpgrowth(spark):
    got = itemsets.fpgrowth(records.make(corpus.mixed_items(spark, SF)), 0.05).collect()
    return {tuple(r["items"]): r["freq"] for r in got}


def test_mixed_sets_of_every_length(spark):
    want = mixed_by_fpgrowth(spark)
    got = {tuple(r["items"].split("|")): r["freq"] for r in RUNS["b_apriori_mixed"](spark, SF).collect()}
    assert max(map(len, want)) > 4 and got == want
    above = {(s[:i] + s[i + 1 :], f) for s, f in want.items() for i in range(len(s))}
    closed = {s: f for s, f in want.items() if (s, f) not in above}
    assert {tuple(r["items"].split("|")): r["freq"] for r in RUNS["b_closed"](spark, SF).collect()} == closed
    sizes = {k: sum(len(s) == k for s in want) for k in set(map(len, want))}
    assert {r["k"]: r["size"] for r in RUNS["d_strata"](spark, SF).collect()} == sizes
    assert RUNS["c_queue"](spark, SF).count() == RUNS["c_chain"](spark, SF).count() == len(want)


def test_rules_of_every_length(spark):
    sets = [tuple(r["items"].split("|")) for r in RUNS["b_apriori_events"](spark, SF).collect()]
    want = {(x, i) for s in sets if len(s) > 1 for i in s for x in combinations(s, len(s) - 1) if i not in x}
    got = {(tuple(r["lhs"].split("|")), r["rhs"]) for r in RUNS["b_rules"](spark, SF).collect()}
    assert max(map(len, sets)) > 2 and got == want


def test_a_bound_on_length_is_reported(spark):
    df = spark.createDataFrame([(["a", "b", "c"],)] * 4, "items array<string>")
    with pytest.warns(UserWarning, match="more than 2 items"):
        assert itemsets.apriori(df, "0.5", max_k=2).truncated


def test_all_combinations_are_labelled_and_served(spark):
    want = {"|".join(x) for x in mixed_by_fpgrowth(spark)}
    ids = lambda name, key="item_id": {r[key] for r in RUNS[name](spark, SF).select(key).distinct().collect()}
    assert ids("c_ballots") == ids("c_vote_pooled") == ids("c_kb", "items") == want
    assert RUNS["e_json"](spark, SF).count() == len(want)
    parts = {r[0] for r in spark.read.parquet(f"{SF}/part.parquet").select("p_partkey").collect()}
    for name in ("c_lexical", "c_narrowing", "a_narrow", "a_flat"):
        assert ids(name) == parts, name


def test_unrolled_sql_reaches_every_level(spark):
    from opatlas.queries.mining import DEEPEST

    sizes = [r["k"] for r in RUNS["b_level_stats"](spark, SF).where("frequent > 0").collect()]
    assert 8 <= max(sizes) < DEEPEST


def test_counts_by_level_of_the_larger_tables(spark):
    """The sizes known of the mixed records: 2,562 sets."""
    got = {r.k: r for r in RUNS["b_level_stats"](spark, "/root/testdata/sf0.01").collect()}
    assert [got[k].frequent for k in range(1, 9)] == [16, 110, 382, 683, 753, 460, 138, 20]
    assert all(r.generated == r.pruned + r.counted and r.frequent <= r.counted for r in got.values()) and got[2].generated == 120


def test_the_sample_joins_three_draws(spark):
    rows = RUNS["d_sample"](spark, SF).collect()
    assert len(rows) == len({r["items"] for r in rows}) == 150
    by = {d: [set(r["items"].split("|")) for r in rows if r["draw"] == d] for d in ("length", "similar", "rare")}
    assert [len(by[d]) for d in ("length", "similar", "rare")] == [100, 25, 25]
    assert all(any(len(x) == len(y) and len(x & y) == len(x) - 1 for y in by["length"]) for x in by["similar"])


def test_json_entries_parse(spark):
    import json

    entries = [json.loads(r["json"]) for r in RUNS["e_json"](spark, SF).limit(50).collect()]
    assert all(e["combo"]["support"] >= 0.05 and set(e["votes"]) == {e["l3"]} and 0 < e["confidence"] <= 1 for e in entries)


def test_retrieval_prompts_name_what_was_found(spark):
    rows = RUNS["e_rag_prompt"](spark, SF).collect()
    assert all(r["prompt"].startswith("Demand: ") and "\nKnown functions:\n1. " in r["prompt"] and r["prompt"].endswith("\nWrite the script.") for r in rows)


def test_recall_of_all_vectors(spark):
    import numpy as np

    rows = spark.read.parquet(f"{SF}/embeddings.parquet").orderBy("vec_id").collect()
    x = np.array([r["embedding"] for r in rows], float)

    def near(v):
        d = np.round(((v[:, None] - v[None]) ** 2).sum(-1), 6)
        np.fill_diagonal(d, np.inf)
        return np.argsort(d, axis=1, kind="stable")[:, :10]

    want = np.mean([len(set(a) & set(b)) / 10 for a, b in zip(near(x), near(x[:, :2]), strict=True)])
    assert RUNS["a_trust"](spark, SF).first()["recall"] == pytest.approx(want, abs=2e-3)


def test_symmetric_affinities_of_every_vector(spark):
    rows = spark.read.parquet(f"{SF}/embeddings.parquet").select("vec_id", "label").collect()
    sizes = {c: sum(r.label == c for r in rows) for c in {r.label for r in rows}}
    got = RUNS["a_tsne_sym"](spark, SF).collect()
    assert {r.i for r in got} == {r.vec_id for r in rows if sizes[r.label] > 1}
    assert len(got) == sum(n * (n - 1) for n in sizes.values()) and sum(r.p for r in got) == pytest.approx(1, abs=1e-4)


def test_model_selection_takes_the_defaults(spark, monkeypatch):
    """K = 1..500 and the library's own steps, iterations and landmarks."""
    from opatlas.operators import gmm, tsne

    asked = []
    monkeypatch.setattr(gmm, "sweep", lambda points, ks, **how: asked.append((ks, how)) or {})
    monkeypatch.setattr(gmm, "coarse_sweep", lambda points, most, **how: asked.append((most, how)) or {})
    monkeypatch.setattr(tsne, "fit", lambda points, **how: asked.append(how))
    for name in ("a_gmm_sweep", "a_gmm_coarse", "a_tsne_fit", "a_tsne_landmark", "a_tsne_cells"):
        RUNS[name](spark, SF)
    n = min(500, spark.read.parquet(f"{SF}/embeddings.parquet").count())
    assert asked == [(list(range(1, n + 1)), {}), (n, {}), {}, {"method": "landmark"}, {"method": "cells"}]
