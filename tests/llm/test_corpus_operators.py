"""Classifier, chat, near-duplicates, mixing and the pipeline against brute force, held-out rows and odd inputs."""

import hashlib
import json
import random
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

import corpus_pipeline
from opatlas.llm import chat_format, mixing, quality_model, quality_rules, simhash
from opatlas.llm.common import table

SF = "/root/testdata/sf0.01"
SMALL = "/root/testdata/sf0.001"


# --- classifier ---------------------------------------------------------------------------


def test_held_out_accuracy(spark):
    got = quality_model.digest(table(spark, SF, "documents"), table(spark, SF, "labels")).join(table(spark, SF, "labels"), "doc_id").toPandas()
    assert (got["held_out"] == got["doc_id"].map(lambda i: zlib.crc32(str(i).encode()) % 5 == 0)).all()
    held = got[got["held_out"]]
    assert (held["predicted"] == held["quality"]).mean() > 0.95
    assert held["score"].between(0, 1).all() and ((held["score"] >= 0.3) == (held["predicted"] == 1)).all()


def test_trees_fit_and_traverse():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(4000, 5))
    y = ((x[:, 0] > 0) ^ (x[:, 1] > 0.3)).astype(float)
    m = quality_model.fit(x[:3000], y[:3000])
    assert ((m.score(x[3000:]) > 0.5) == y[3000:]).mean() > 0.95
    row = x[3000]
    total = m.start
    for f, t, v in zip(m.feature, m.threshold, m.leaf, strict=True):
        i = 0
        while i < len(f):
            i = 2 * i + 1 + (row[f[i]] > t[i])
        total += v[i - len(f)]
    assert m.score(x[3000:3001])[0] == pytest.approx(1 / (1 + np.exp(-total)))


def test_classifier_odd(spark, odd, none):
    no_labels = spark.createDataFrame([], "doc_id long, quality long")
    assert all(r.score == pytest.approx(0.5) for r in quality_model.digest(odd, no_labels).collect())
    one = spark.createDataFrame([(1, 1), (1, None), (None, 1), (6, 1), (99, 0)], "doc_id long, quality long")
    got = quality_model.digest(odd, one)
    assert got.count() == odd.count() and got.where("score IS NULL").count() == 0
    assert quality_model.digest(none, one).count() == 0
    assert quality_model.keep(odd, one).columns == odd.columns


def test_labels_of_the_held_out_fold_are_not_learnt(spark):
    docs, labels = table(spark, SF, "documents"), table(spark, SF, "labels")
    flipped = labels.withColumn("quality", F.when(quality_model.held_out(F.col("doc_id")), 1 - F.col("quality")).otherwise(F.col("quality")))
    a, b = quality_model.train(docs, labels), quality_model.train(docs, flipped)
    assert (a.leaf == b.leaf).all() and (a.threshold == b.threshold).all()


# --- chat ---------------------------------------------------------------------------------

SAID = "<|im_end|><|im_start|>assistant ok"


def brute_chat(rows):
    out = {}
    for conv in {r[0] for r in rows}:
        t = sorted((r for r in rows if r[0] == conv), key=lambda r: (r[1] is not None, r[1]))
        turns = "".join(f"{r[2] or ''}\n{r[3] or ''}\n" for r in t)
        loss = "".join(r[3] or "" for r in t if r[2] == "assistant")
        out[conv] = (len(t), hashlib.sha256(turns.encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest())
    return out


def test_chat_digest(spark):
    rng = random.Random(4)
    bits = ["<|", "|>", "<\\|", "<\\\\|", "<", "|", "\\", "\n", "<|im_end|>\n", "<|im_start|>user\n", "é😀", "ok "]
    rows = [(c, t, rng.choice(["user", "assistant", "system", None, "a\nb\\n"]), rng.choice([None, "", "".join(rng.choices(bits, k=9))])) for c in (1, 2, None) for t in range(8)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("conv", F.lit("x"))
    got = {r.conv_id: r for r in chat_format.digest(df.repartition(5)).collect()}
    want = brute_chat([*rows, (-1, 0, "user", SAID), (-1, 1, "assistant", SAID)])
    assert {k: (r.n_turns, r.turns_sha256, r.loss_chars, r.loss_sha256) for k, r in got.items()} == want
    assert set(r.conv_id for r in chat_format.digest(df.limit(0)).collect()) == {-1}


def test_chat_text_and_spans(spark):
    df = spark.createDataFrame([(1, 0, "user", "a"), (1, 1, "assistant", "b<|c"), (1, 2, "assistant", None)], "conv_id long, turn long, role string, text string")
    r = chat_format.conversations(df).first()
    assert chat_format.parse(r.formatted) == [("user", "a"), ("assistant", "b<|c"), ("assistant", "")]
    assert [chat_format.unescape(r.formatted[s.start : s.end]) for s in r.loss_spans] == ["b<|c", ""]
    assert len(r.formatted) == next(x.formatted_chars for x in chat_format.read_back(chat_format.segments(df)).collect())
    with pytest.raises(ValueError):
        chat_format.parse("x" + r.formatted)


def test_chat_layouts(spark):
    records = [
        {"messages": [{"role": "user", "content": "q"}, {"role": "assistant", "content": "a"}]}, {"conversations": [{"from": "human", "value": "q"}, {"from": "gpt", "value": "a"}]},
        {"prompt": "q", "completion": "a"}, {"instruction": "q", "input": "", "output": "a"}, {"instruction": "q", "output": "a"}, {"question": "q", "answer": "a"},
        {"messages": [{"role": "user", "content": "q", "name": "n"}, {"role": "assistant", "content": "a"}], "id": 3, "meta": {"score": [1]}},
    ]
    rows = [(i, json.dumps(r)) for i, r in enumerate(records)] + [
        (90, "{"), (91, None), (92, '{"other": 1}'), (93, json.dumps({"instruction": "q", "input": "more", "output": "a"})), (94, '{"turn": 5, "role": "human", "text": null}'),
        (95, '{"prompt": "q", "messages": [{"role": "user", "content": "q"}]}'), (96, "[]"), (97, '{"messages": [null, 3, {"role": "user", "content": null}]}'),
    ]
    got = chat_format.canonical_turns(spark.createDataFrame(rows, "id long, j string"), "id", "j").toPandas()
    for i in range(len(records)):
        part = got[got["conv_id"] == i]
        assert list(zip(part["role"], part["text"], strict=True)) == [("user", "q"), ("assistant", "a")]
    assert got[got["conv_id"].isin((90, 91, 92, 95, 96))]["turn"].isna().all() and got[got["conv_id"] == 93]["text"].iloc[0] == "q\n\nmore"
    assert got[got["conv_id"] == 97][["role", "text"]].values.tolist() == [["", ""], ["", ""], ["user", ""]]
    assert got[got["conv_id"] == 94][["turn", "role", "text"]].values.tolist() == [[5, "human", ""]]
    assert len({chat_format.fingerprint(m.paths) for m in chat_format.MAPPINGS}) == len(chat_format.MAPPINGS)


def test_chat_digests_through_many_layouts(spark):
    """The given conversations as tables of four layouts and as JSON: each is found by its fingerprint and gives equal digests."""
    turns = table(spark, SMALL, "conversations").withColumn("a.b", F.lit(1))
    want = {r.conv_id: tuple(r) for r in chat_format.digest(turns).collect()}
    assert len(want) == turns.select("conv_id").distinct().count() + 1
    listed = turns.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))).alias("t"))
    other = F.create_map(*map(F.lit, ("user", "human", "assistant", "GPT", "system", "system")))
    shaped = {
        "messages": listed.select("conv_id", F.lit("x").alias("id"), F.transform("t", lambda x: F.struct(x["role"], x["text"].alias("content"), F.lit(0.5).alias("score"))).alias("messages")),
        "dialogue": listed.select("conv_id", F.transform("t", lambda x: F.struct(other[x["role"]].alias("from"), x["text"].alias("value"))).alias("conversations")),
    }
    # two-turn conversations as a prompt and its completion
    two = listed.where("size(t) = 2 AND t[0].role = 'user' AND t[1].role = 'assistant' AND t[0].text <> '' AND t[1].text <> ''")
    shaped["prompt_completion"] = two.select("conv_id", F.col("t")[0]["text"].alias("prompt"), F.col("t")[1]["text"].alias("completion"))
    for name, df in shaped.items():
        assert chat_format.layout_of(chat_format.schema_paths(df.schema))[1].name == name
        got = {r.conv_id: tuple(r) for r in chat_format.digest(df).collect()}
        assert got == {k: want[k] for k in got} and len(got) == df.count() + 1 > 1, name
        raw = df.select("conv_id", F.to_json(F.struct(*df.columns[1:])).alias("j"))
        back = chat_format.canonical_turns(raw, "conv_id", "j").where("turn IS NOT NULL")
        assert {r.conv_id: tuple(r) for r in chat_format.read_back(chat_format.segments(back)).collect()} == {k: v for k, v in got.items() if k != -1}, name
    with pytest.raises(ValueError, match="no mapping"):
        chat_format.canonical(turns.drop("role"))


def test_chat_lists_with_nulls(spark):
    rows = [(1, None), (2, []), (3, [None, ("human", None), (None, "x")])]
    df = spark.createDataFrame(rows, "conv_id long, messages array<struct<role: string, content: string>>")
    got = sorted(map(tuple, chat_format.canonical(df).collect()))
    assert got == [(3, 0, "", ""), (3, 1, "user", ""), (3, 2, "", "x")]


# --- near duplicates ----------------------------------------------------------------------


def brute_print(text):
    w = (text or "").encode().lower().split()
    s = [b" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else [b" ".join(w)] if w else []
    h = [xxhash.xxh64_intdigest(x, 42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0


def brute_components(prints):
    root = {i: i for i in prints}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(prints)
    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            if (prints[a] ^ prints[b]).bit_count() <= 2:
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {i: find(i) for i in ids}


def test_fingerprints(spark, odd):
    texts = {r.doc_id: r.text for r in odd.collect()}
    for r in simhash.digest(odd).collect():
        assert r.fingerprint == f"{brute_print(texts[r.doc_id]):016x}"
    assert simhash.digest(odd.limit(0)).count() == 0


def test_components_of_given_documents(spark):
    docs = table(spark, SMALL, "documents")
    prints = {r.doc_id: brute_print(r.text) for r in docs.collect()}
    want = brute_components(prints)
    assert {r.doc_id: r.component_id for r in simhash.digest(docs).collect()} == want


def test_rows_without_an_id_link_others(spark):
    """Fingerprints two bits apart in a chain whose middle has no id."""
    words = [f"word{i}" for i in range(30)]
    rows, prints = [], {}
    for i in range(4000):
        w = list(words)
        w[i % 30] = f"x{i}"
        prints[" ".join(w)] = brute_print(" ".join(w))
    texts = sorted(prints, key=lambda t: prints[t])
    near = lambda a, b: (prints[a] ^ prints[b]).bit_count()
    a, b, c = next((a, b, c) for b in texts for a in texts for c in texts if 0 < near(a, b) <= 2 and 0 < near(b, c) <= 2 and near(a, c) > 2)
    rows = [(5, a), (None, b), (9, c), (None, "quite another text")]
    got = [(r.doc_id, r.component_id) for r in simhash.digest(spark.createDataFrame(rows, "doc_id long, text string")).collect()]
    assert sorted(got, key=str) == [(5, 5), (9, 5), (None, 5), (None, None)]


def near_by_hand(texts):
    """First id of each text's group: all pairs of five-word shingle sets."""
    sets = {}
    for i, t in texts.items():
        w = (t or "").encode().lower().split()
        sets[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()
    root = {i: i for i in texts}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(texts)
    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            x, y = sets[a], sets[b]
            small, large = sorted((len(x), len(y)))
            if small >= 0.8 * large and (x == y or (both := len(x & y)) and both >= 0.8 * (len(x) + len(y) - both)):
                p, q = sorted((find(a), find(b)))
                root[q] = p
    return {i: find(i) for i in ids}


def groups_of(docs):
    nodes = {r.node: r.root for r in simhash.near_groups(docs).collect()}
    md5 = lambda t: hashlib.md5((t or "").encode()).hexdigest()
    roots = {r.doc_id: nodes[md5(r.text)] for r in docs.collect()}
    first = {}
    for i in sorted(roots):
        first.setdefault(roots[i], i)
    return {i: first[r] for i, r in roots.items()}


def test_near_groups_of_given_documents(spark):
    docs = table(spark, SMALL, "documents")
    want = near_by_hand({r.doc_id: r.text for r in docs.collect()})
    assert groups_of(docs) == want
    assert sorted(r.doc_id for r in simhash.dedup(docs).collect()) == sorted(i for i, c in want.items() if i == c)


def test_near_groups_of_edited_texts(spark):
    """Chains of edits of short and long texts, texts that share a long passage only, and texts of few words."""
    rng = random.Random(11)
    pool = [f"w{i}" for i in range(3000)]
    texts, passage = {}, " ".join(rng.choices(pool, k=60))
    for base in range(14):
        w = rng.choices(pool, k=rng.choice([6, 9, 20, 60, 200, 900, 3000]))
        for _ in range(9):
            texts[len(texts)] = " ".join(w).upper() if rng.random() < 0.1 else "  ".join(w)
            for _ in range(max(1, len(w) // rng.choice([30, 60, 400]))):
                k = rng.randrange(len(w))
                w[k : k + 1] = rng.choice([[], [rng.choice(pool)], [w[k], rng.choice(pool)]])
    for _ in range(30):
        texts[len(texts)] = " ".join(rng.choices(pool, k=rng.randint(10, 300))) + " " + passage
    for t in ("", " \n", None, "a", "A", "a b c d", "a b c d e", "a b c d e f"):
        texts[len(texts)] = t
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string").repartition(5)
    assert groups_of(docs) == near_by_hand(texts)


@pytest.mark.parametrize("hubs", [1, 0])
def test_near_groups_of_crowded_buckets(spark, monkeypatch, hubs):
    """A pair is found whatever the size of its bucket, also where no hub and no third text ties it."""
    monkeypatch.setattr(simhash, "CROWD", 1)
    monkeypatch.setattr(simhash, "HUBS", hubs)
    monkeypatch.setattr(simhash, "BLOCK", 5)
    rng = random.Random(12)
    pool, texts = [f"w{i}" for i in range(3000)], {}
    for _ in range(12):
        w = rng.choices(pool, k=120)
        for _ in range(8):
            texts[len(texts)] = " ".join(w)
            w[rng.randrange(len(w))] = rng.choice(pool)
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string").repartition(5)
    assert groups_of(docs) == near_by_hand(texts)


def test_near_groups_of_many_unlike_texts_in_a_bucket(spark, monkeypatch):
    """Members of a large bucket that are near, but not near enough, make no pairs as rows; those that are near enough are found."""
    monkeypatch.setattr(simhash, "CROWD", 8)
    rng, counts, verified = random.Random(13), [], simhash.verified
    monkeypatch.setattr(simhash, "verified", lambda pairs, *a: (counts.append(pairs.count()), verified(pairs, *a))[1])
    pool, texts = [f"w{i}" for i in range(3000)], {}
    base = rng.choices(pool, k=150)
    for i in range(200):
        w = base[:]
        for at in rng.sample(range(150), 4):
            w[at] = rng.choice(pool)
        texts[i] = " ".join(w)
        if i % 5 == 0:
            w[0] = rng.choice(pool)
            texts[1000 + i] = " ".join(w)
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string").repartition(5)
    want = near_by_hand(texts)
    assert 100 < len(set(want.values())) < len(want)
    assert groups_of(docs) == want
    assert counts[1] < 2 * len(texts)  # beside what is compared with hubs


def test_block_links_by_hand(monkeypatch):
    """Shared shingles are counted alike by products and by postings; links tie what pairs by hand tie."""
    rng = random.Random(14)
    sets = [np.unique(np.array([rng.randrange(60) for _ in range(rng.choice([0, 1, 5, 30]))], "<i8")) for _ in range(90)]
    sets += [np.unique(np.append(s, 99)) for s in sets[:40]]
    part = lambda ids: (np.array(ids), np.array(ids) // 2, np.array([len(sets[i]) for i in ids]), np.concatenate([sets[i] for i in ids]))
    a, b = part(list(range(0, 130, 2))), part(list(range(1, 130, 2)))
    want = [[len(np.intersect1d(sets[i], sets[j])) for j in b[0]] for i in a[0]]
    for dense in (0, 20, 1 << 30):
        monkeypatch.setattr(simhash, "DENSE", dense)
        monkeypatch.setattr(simhash, "_PAIRS", 100)
        assert simhash.shared_counts(*a[2:], *b[2:]).tolist() == want
    alike = [(i, j) for x, i in enumerate(a[0]) for y, j in enumerate(b[0]) if i // 2 != j // 2 and want[x][y] >= 0.8 * (len(sets[i]) + len(sets[j]) - want[x][y]) - 1e-9]

    def roots(pairs):
        top = list(range(65))
        for _ in top:
            for i, j in pairs:
                top[i // 2] = top[j // 2] = min(top[i // 2], top[j // 2])
        return top

    got = simhash.block_links(a, b)
    assert roots(got) == roots(alike) and len(got) == 65 - len(set(roots(alike))) and {tuple(sorted(p)) for p in got} <= {tuple(sorted(map(int, p))) for p in alike}


@pytest.mark.parametrize("crowd", [simhash.CROWD, 3, 0])
def test_links_of_random_fingerprints(spark, monkeypatch, crowd):
    """Chains and crowds of near fingerprints, by either way of linking a cell."""
    monkeypatch.setattr(simhash, "CROWD", crowd)
    rng = random.Random(crowd)
    prints, fp = {}, rng.getrandbits(64)
    for i in range(160):
        if i % 40 == 0:
            fp = rng.getrandbits(64)
        for _ in range(rng.randint(0, 3)):
            fp ^= 1 << rng.randrange(64)
        prints[i] = fp
    first = {}
    for i, f in prints.items():
        first.setdefault(f, i)
    signed = [(f - (1 << 64) if f >> 63 else f, i) for f, i in first.items()]
    edges = simhash.links(spark.createDataFrame(signed, "fp long, id long"))
    assert all((prints[r.lo] ^ prints[r.hi]).bit_count() <= 2 for r in edges.collect())
    roots = {r.node: r.root for r in simhash.components(edges).collect()}
    want = brute_components({i: f for f, i in first.items()})
    assert {i: roots.get(i, i) for i in want} == want


def test_dedup_odd(odd, none):
    kept = simhash.dedup(odd)
    assert kept.columns == odd.columns and simhash.dedup(none).count() == 0
    ids = [r.doc_id for r in kept.collect()]
    # one row of document 1, the null and blank texts are one group, the row without an id is one of its own
    assert sorted(ids, key=str) == [1, 2, 5, 6, 7, 8, None]
    again = sorted(map(str, simhash.dedup(odd.withColumn("lang", odd.doc_id.cast("string")).repartition(3)).collect()))
    assert again == sorted(map(str, simhash.dedup(odd.withColumn("lang", odd.doc_id.cast("string")).repartition(7)).collect()))


# --- mixing -------------------------------------------------------------------------------


def test_targets():
    assert mixing.targets([100, 100, 100], [5, 2, 1]) == [200.0, pytest.approx(500 / 3), pytest.approx(250 / 3)]
    sizes, weights = [10, 500, 30, 0, 7], [5, 2, 1, 5, 2]
    t = mixing.targets(sizes, weights)
    assert sum(t) == pytest.approx(1.5 * sum(sizes)) and all(a <= 2 * s for a, s in zip(t, sizes, strict=True)) and t[3] == 0
    assert mixing.targets([], []) == []


def test_split_tree_is_exact():
    q = np.array([100, 7, 0, 33])
    got = mixing.split_tree(q, 12, np.random.default_rng(1))
    assert (got.sum(axis=0) == q).all() and got.min() >= 0 and np.ptp(got.sum(axis=1)) <= 1


def test_mixing(spark):
    docs = table(spark, SF, "documents")
    rows = mixing.account(docs).join(docs.select("doc_id", "source"), "doc_id").toPandas()
    by = rows.groupby("source").agg(size=("size", "sum"), stated=("source_size", "first"), target=("target", "first"), taken=("taken", "sum"))
    assert (by["size"] == by["stated"]).all() and (rows["taken"] <= 2 * rows["size"]).all()
    assert ((by["taken"] - by["target"]).abs() <= 0.02 * by["target"]).all()
    again = mixing.account(docs.repartition(7)).join(docs.select("doc_id", "source"), "doc_id").toPandas()
    cols = ["doc_id", "taken", "target"]
    assert rows.sort_values(cols)[cols].to_numpy().tolist() == again.sort_values(cols)[cols].to_numpy().tolist()
    mixed = mixing.mix(docs, 8, "shard").toPandas()
    assert mixed.groupby("doc_id").size().to_dict() == {i: len(s) for i, s in zip(rows["doc_id"], rows["shards"], strict=True) if len(s)}
    assert set(mixed["shard"]) == set(range(8))


def test_shards_follow_the_words(spark, monkeypatch):
    docs = table(spark, SF, "documents")
    words = 1.5 * sum(r.source_size for r in mixing.account(docs).select("source_size", "target").distinct().collect())
    monkeypatch.setattr(mixing, "SHARD_WORDS", 10_000)
    got = mixing.mix(docs, shard_column="shard").select("shard").distinct().count()
    assert got == -(-int(words) // 10_000) > 20
    monkeypatch.setattr(mixing, "MAX_SHARDS", 7)
    assert mixing.mix(docs, shard_column="shard").select("shard").distinct().count() == 7


def test_mixing_odd(odd, none):
    got = mixing.account(odd)
    assert got.count() == odd.count() and got.where("taken > 2 * size OR taken IS NULL").count() == 0
    assert {r.doc_id: r["size"] for r in got.collect()}[2] == 0
    assert mixing.account(none).count() == 0 and mixing.mix(none).count() == 0
    assert mixing.mix(odd).columns == odd.columns


# --- pipeline -----------------------------------------------------------------------------


def test_pipeline(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = {}
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, SF)
        out.write.parquet(str(tmp_path / name))
        before, docs = docs, spark.read.parquet(str(tmp_path / name))
        kept[name] = [r.doc_id for r in docs.select("doc_id").collect()]
        assert set(kept[name]) <= {r.doc_id for r in before.select("doc_id").collect()}
        assert name == "piece_sampling" or docs.columns == before.columns
    assert sorted(kept["quality_rules"]) == sorted(r.doc_id for r in quality_rules.digest(spark.read.parquet(f"{SF}/documents.parquet")).where("kept").collect())
    two = spark.read.parquet(str(tmp_path / "quality_classifier"))
    assert sorted(kept["simhash_dedup"]) == sorted(i for i, c in near_by_hand({r.doc_id: r.text for r in two.collect()}).items() if i == c)
    three = spark.read.parquet(str(tmp_path / "simhash_dedup"))
    taken = {r.doc_id: len(r.shards) for r in mixing.account(three).collect() if r.shards}
    assert {i: kept["source_mixing"].count(i) for i in set(kept["source_mixing"])} == taken
    assert docs.where("NOT lossless").count() == 0
    good = {r.doc_id for r in table(spark, SF, "labels").where("quality = 1").collect()}
    one = set(kept["quality_rules"])
    assert len(good & one & set(kept["quality_classifier"])) >= 0.98 * len(good & one)
    assert sorted(map(tuple, corpus_pipeline.run(spark, SF).drop("ids").collect())) == sorted(map(tuple, docs.drop("ids").collect()))


def test_stages_take_odd_rows(spark, odd, none, clashing):
    for docs in (odd, none, clashing):
        for name, stage in corpus_pipeline.STAGES:
            out = stage(spark, docs, SMALL)
            assert out.count() <= 2 * docs.count(), name
            assert name == "piece_sampling" or out.columns == docs.columns
            if docs is clashing and name != "piece_sampling":
                want = {str(r) for r in docs.collect()}
                assert {str(r) for r in out.collect()} <= want, name


def test_clashing_columns(spark, clashing, odd):
    from opatlas.llm import media, piece_sampling, token_counts
    from opatlas.llm.registry import tokenizer_path

    led = quality_rules.ledger(clashing)
    assert {"_n_words", "n_words", "_rule_bits", "rule_bits", "a.b", "nested.one"} <= set(led.columns) and len(led.columns) == len(clashing.columns) + 6
    assert {r["_rule_bits"] for r in led.collect()} == {"rule_bits"}
    assert sorted(map(str, led.select(*quality_rules.MEASURES, "rule_bits").collect())) == sorted(map(str, quality_rules.ledger(odd).select(*quality_rules.MEASURES, "rule_bits").collect()))
    path = tokenizer_path("piece_bpe_32k.model")
    got = piece_sampling.sample_pieces(clashing, path, keep=("doc_id", "ids", "N_Pieces", "_key", "a.b", "nested.one"))
    assert got.columns == ["doc_id", "_ids", "_N_Pieces", "_key", "a.b", "nested.one", "ids", "n_pieces", "lossless"]
    assert all(r.lossless and r["_ids"] == "ids" and r["nested.one"]["c.d"] == 1 for r in got.collect())
    assert piece_sampling.decode_pieces(got.withColumn("decoded", F.lit(1)), path).columns[-2:] == ["_decoded", "decoded"]
    mixed = mixing.mix(clashing, shard_column="shard")
    assert "_shard" in mixed.columns and "__shard" in mixed.columns and mixed.columns[-1] == "shard" and mixed.count() > 0
    pixels = media.pixel_arrays(media.store_texts(odd).select("doc_id", "media", F.lit("i").alias("image"), F.lit(1).alias("a.b")))
    assert pixels.columns == ["doc_id", "media", "_image", "a.b", "image", "height", "width", "argb"] and pixels.where("image = 0").count() == odd.count()
    for run in (simhash.digest, token_counts_of(token_counts, tokenizer_path), media.store_texts, mixing.account):
        assert run(clashing).count() == odd.count()


def token_counts_of(module, path):
    return lambda docs: module.count_tokens(docs, path("byte_bpe_50k.json"))
