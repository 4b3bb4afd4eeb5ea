"""Rules, tokens, pieces, media, pages and urls against plain Python, exact round trips and odd inputs."""

import hashlib
import html
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from opatlas.llm import html_text, media, piece_sampling, quality_rules, token_counts, url_filters, webp
from opatlas.llm.common import table
from opatlas.llm.registry import oracle_sql, queries, tokenizer_path

SF = "/root/testdata/sf0.001"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def by_id(df, key="doc_id"):
    return {r[key]: r for r in df.collect()}


@pytest.mark.parametrize("name", sorted(oracle_sql()))
def test_sql(spark, name):
    import sys

    sys.path.insert(0, "tests")
    import oracle

    assert oracle.differences(queries()[name](spark, SF), oracle.connect(SF), oracle_sql()[name]) == []


# --- rules --------------------------------------------------------------------------------


def rules_of(text):
    w = WORD.findall(text or "")
    windows = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    covered = {j for i in range(len(w) - 4) if windows[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
    lines = [x for x in (text or "").split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text or ""), len(lines) - len(set(lines)), len(covered)


def test_rules(odd, none):
    got = quality_rules.digest(odd).collect()
    assert len(got) == odd.count() and quality_rules.digest(none).count() == 0
    texts = {r.doc_id: r.text for r in odd.collect()}
    for r in got:
        want = rules_of(texts[r.doc_id])
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want, r.doc_id
        assert r.base_failed == (want[0] < 10 or 100 * want[4] > 20 * want[0]) and not (r.base_failed and r.kept)


def test_rules_keep_and_ablation(odd):
    kept = quality_rules.keep(odd)
    assert kept.columns == odd.columns
    assert sorted(r.doc_id or 0 for r in kept.collect()) == sorted(r.doc_id or 0 for r in quality_rules.digest(odd).where("kept").collect())
    led = quality_rules.ledger(odd)
    rows = by_id(quality_rules.ablation(led), "rule")
    assert rows["few_words"].n_failed == led.where("n_words < 10").count()
    full = quality_rules.mask_of(quality_rules.POLICIES["v2"])
    assert rows["few_words"].n_kept_without == sum((r.rule_bits & full & ~1) == 0 for r in led.collect())


# --- tokens -------------------------------------------------------------------------------


def test_tokens_equal_the_library(odd, none):
    from tokenizers import Tokenizer

    path = tokenizer_path("byte_bpe_50k.json")
    lib = Tokenizer.from_file(path)
    count = token_counts.Counter(token_counts.vocabulary(path))
    rng = random.Random(1)
    pool = [*map(chr, range(256)), *map(chr, (0x1680, 0x2028, 0x202F, 0x3000, 0x200B, 0x4E2D, 0x1F600, 0x300, 0x661, 0xBD)), "'s", "'ll", "<|endoftext|>", "  ", " the", " ab12"]
    texts = ["".join(rng.choices(pool, k=rng.randint(0, 50))) for _ in range(1500)] + ["ab" * 3000, " " * 500, "<|endoftext|>" * 3]
    assert [count(t) for t in texts] == [len(e.ids) for e in lib.encode_batch(texts, add_special_tokens=False)]
    got = token_counts.count_tokens(odd, path).collect()
    texts = {r.doc_id: r.text or "" for r in odd.collect()}
    assert all(r.n_tokens == len(lib.encode(texts[r.doc_id], add_special_tokens=False).ids) and r.n_bytes == len(texts[r.doc_id].encode()) for r in got)
    assert len(got) == odd.count() and token_counts.count_tokens(none, path).count() == 0


def test_proven_strings_are_one_token():
    from tokenizers import Tokenizer

    path = tokenizer_path("byte_bpe_50k.json")
    lib, v = Tokenizer.from_file(path), token_counts.vocabulary(path)
    some = random.Random(2).sample(sorted(v.proven), 3000)
    assert all(len(e.ids) == 1 for e in lib.encode_batch(some, add_special_tokens=False)) and len(v.proven) > 40_000


# --- pieces -------------------------------------------------------------------------------


def test_pieces_are_sampled_exactly():
    p = piece_sampling.pieces(tokenizer_path("piece_bpe_32k.model"))
    unit = " hello"

    def every(i):
        if i == len(unit):
            yield (), 0.0
        for j in range(i + 1, len(unit) + 1):
            if unit[i:j] in p.ids:
                yield from (((p.ids[unit[i:j]], *rest), p.weight[unit[i:j]] + w) for rest, w in every(j))

    all_ = dict(every(0))
    total = sum(np.exp(w) for w in all_.values())
    n = 20_000
    ids, at = piece_sampling.Sampler(p)(["hello"] * n, np.arange(n) * 7919)
    seen = Counter(tuple(ids[at[i] : at[i + 1]]) for i in range(n))
    assert set(seen) <= set(all_)
    assert max(abs(seen[s] / n - np.exp(w) / total) for s, w in all_.items()) < 0.012


def test_likeliest_pieces_by_enumeration(spark, odd, none, monkeypatch):
    path = tokenizer_path("piece_bpe_32k.model")
    p = piece_sampling.pieces(path)

    def best(unit):
        ways = [0.0]
        for j in range(1, len(unit) + 1):
            ways.append(max(ways[i] + p.weight.get(unit[i:j], p.byte_weight * len(unit[i:j].encode()) if j - i == 1 else -1e9) for i in range(j)))
        return ways[-1]

    rng = random.Random(5)
    for _ in range(200):
        t = "".join(rng.choices([*"abcdefghij \n.é中", "the ", "ing", "tion"], k=rng.randint(1, 20)))
        ids = piece_sampling.encode_best(t, p)
        assert piece_sampling.decode(ids, p) == t
        got = sum(p.weights[i] if p.texts[i].decode(errors="replace") in p.ids else p.byte_weight for i in ids)
        assert got == pytest.approx(best(" " + t)), t
    long = "".join(rng.choices("abcdefgh ", k=3000))
    want = piece_sampling.encode_best(long, p)
    monkeypatch.setattr(piece_sampling, "LEARN", 64)
    monkeypatch.setattr(piece_sampling, "CACHE", 100)
    assert piece_sampling.encode_best(long, p) == want
    rows = piece_sampling.encode_pieces(odd, path).collect()
    assert len(rows) == odd.count() and all(r.lossless for r in rows) and piece_sampling.encode_pieces(none, path).count() == 0


def test_pieces_round_trip_and_repeat(odd, none):
    path = tokenizer_path("piece_bpe_32k.model")
    p = piece_sampling.pieces(path)
    rng = random.Random(3)
    pool = [*" ab\n\t.,▁é中ÿ\x00", "▁▁", "  ", "\U0001f600", "the ", "ing"]
    for _ in range(300):
        t = "".join(rng.choices(pool, k=rng.randint(0, 40)))
        assert piece_sampling.decode(piece_sampling.encode(t, 5, p), p) == t
    got = piece_sampling.sample_pieces(odd, path)
    rows = sorted(got.collect(), key=str)
    assert all(r.lossless for r in rows) and len(rows) == odd.count()
    assert rows == sorted(piece_sampling.sample_pieces(odd.repartition(5), path).collect(), key=str)
    assert piece_sampling.sample_pieces(none, path).count() == 0
    back = by_id(piece_sampling.decode_pieces(got.where("doc_id = 5"), path))
    assert back[5].decoded == by_id(odd.where("doc_id = 5"))[5].text


# --- media --------------------------------------------------------------------------------


def test_webp_tools_round_trip():
    rng = np.random.default_rng(1)
    for _ in range(12):
        h, w = (int(x) for x in rng.integers(1, 12, 2))
        c = rng.integers(0, int(rng.choice([2, 4, 256])), (h, w, 4))
        tiles = (-(-h >> 2), -(-w >> 2))
        tools = (
            {}, {"green": True}, {"predictor": rng.integers(0, 14, tiles)}, {"cross": rng.integers(0, 256, (*tiles, 4))}, {"cache_bits": 4}, {"references": True},
            {"predictor": rng.integers(0, 14, tiles), "cross": rng.integers(0, 256, (*tiles, 4)), "green": True, "references": True, "groups": True, "cache_bits": 3},
        )
        for how in tools:
            assert (webp.decode(webp.encode(c, **how)) == c).all(), how
        for colours in (2, 4, 16, 200):
            q = rng.integers(0, 256, (colours, 4))[rng.integers(0, colours, (h, w))]
            assert (webp.decode(webp.encode(q, palette=True, references=True)) == q).all()


def test_webp_known_file():
    """A one-pixel image written bit by bit from the format's description."""
    out = webp.Out()
    for value, n in ((0x2F, 8), (0, 14), (0, 14), (1, 1), (0, 3), (0, 1), (0, 1), (0, 1)):
        out.write(value, n)
    for symbol in (20, 10, 30, 40, 0):  # green, red, blue, alpha, distance: one symbol each, in eight bits
        out.write(1, 1), out.write(0, 1), out.write(1, 1), out.write(symbol, 8)
    assert webp.decode(webp.container(out.bytes())).tolist() == [[[40, 10, 20, 30]]]


def test_webp_broken_files():
    good = webp.encode(np.random.default_rng(0).integers(0, 256, (6, 6, 4)))
    for bad in (b"", b"RIFF", good[:30], good[:8] + b"XXXX" + good[12:]):
        with pytest.raises((ValueError, IndexError)):
            webp.decode(bad)


def test_media(odd, none):
    got = media.store_texts(odd).collect()
    texts = {r.doc_id: (r.text or "").encode() for r in odd.collect()}
    for r in got:
        p = media.pad(texts[r.doc_id])
        assert len(p) % 64 == 0 and len(p) >= 64 and media.load(bytes(r.media)) == p
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(texts[r.doc_id]), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]))
        assert r.media_sha256 == hashlib.sha256(bytes(r.media)).hexdigest() and r.media_bytes == len(r.media)
    assert len(got) == odd.count() and media.store_texts(none).count() == 0
    twice = [tuple(r) for r in got if r.doc_id == 1]
    assert twice[0] == twice[1]
    big = np.random.default_rng(1).integers(0, 256, media.MAX_IMAGE + 100, np.uint8).tobytes()
    assert media.load(media.store(media.pad(big))) == media.pad(big)


def test_store_uses_its_tools_at_every_size():
    """Palettes, own codes, references and differences make large payloads small, and all come back."""
    rng = np.random.default_rng(2)
    four, sixteen = (rng.integers(0, n, 100_000).astype(np.uint8).tobytes() for n in (4, 16))
    upper = (b"XQZ"[i] for i in rng.choice(3, 50_000, p=[0.98, 0.01, 0.01]))
    passage = rng.integers(0, 256, 20_000, np.uint8).tobytes()
    ramp = (np.cumsum(rng.integers(0, 2, 64_000)) & 255).astype(np.uint8).tobytes()
    most = {four: 25_500, sixteen: 50_500, bytes(upper): 3_000, passage * 4: 21_000, ramp: 13_000, b"x" * 300_000: 400}
    for payload, size in most.items():
        p = media.pad(payload)
        stored = media.store(p)
        assert len(stored) <= size and media.load(stored) == p
    for size in (0, 1, 7, 8, 9, 64, 65, 5_000, 70_000):
        for different in (1, 2, 16, 17, 256):
            p = media.pad(rng.integers(0, different, size).astype(np.uint8).tobytes() * 2)
            assert media.load(media.store(p)) == p


def test_webp_references_across_windows(monkeypatch):
    """The quick reader gives what the reader of single pixels gives, wherever its windows end."""
    rng = np.random.default_rng(3)
    words = [rng.integers(97, 123, int(n)).astype(np.uint8).tobytes() for n in rng.integers(2, 12, 40)]
    samples = np.frombuffer(media.pad(b" ".join(words[int(i)] for i in rng.integers(0, 40, 900))), np.uint8)
    image = webp.container(webp.encode_samples(samples, 64))
    for window in (1, 2, 3, 7, 64, 1 << 15):
        monkeypatch.setattr(webp, "WINDOW", window)
        assert (webp.decode(image)[..., 2].ravel() == samples).all()
    for end in range(30, len(image) - 1, 37):
        with pytest.raises((ValueError, IndexError)):
            webp.decode(image[:end])


def test_pixel_arrays(spark, odd):
    got = media.pixel_arrays(media.store_texts(odd.where("doc_id IN (1, 3)")).select("doc_id", "media")).collect()
    assert all(len(r.argb) == 4 * r.height * r.width for r in got)
    assert bytes(next(r for r in got if r.doc_id == 3).argb[2::4]) == b"\0" * 64
    assert media.pixel_arrays(spark.createDataFrame([(None,)], "media binary")).first().argb is None


def test_pixels_of_every_file(spark):
    """A text of three images gives all of them, numbered in order."""
    text = "".join(chr(33 + i % 89) for i in range(2 * media.MAX_IMAGE + 100))
    docs = spark.createDataFrame([(1, text), (2, "ab")], "doc_id long, text string")
    stored = media.store_texts(docs).select("doc_id", "media")
    got = {(r.doc_id, r.image): bytes(r.argb)[2::4] for r in media.pixel_arrays(stored).collect()}
    assert set(got) == {(1, 0), (1, 1), (1, 2), (2, 0)}
    assert (got[1, 0] + got[1, 1] + got[1, 2]).rstrip(b"\0").decode() == text
    assert media.pixel_arrays(spark.createDataFrame([(None,), (b"",)], "media binary")).where("argb IS NULL").count() == 2


# --- pages --------------------------------------------------------------------------------


def test_articles_of_the_given_pages(spark):
    for r in html_text.extract(table(spark, SF, "pages")).join(table(spark, SF, "pages").select("page_id", "html"), "page_id").collect():
        inside = re.search(r"<article>(.*?)(</article>|$)", r.html, re.S)[1]
        blocks = (" ".join(html.unescape(re.sub(r"<[^>]*>", " ", b)).split()) for b in re.split(r"</?(?:p|h1)>", inside))
        assert r.text == "\n\n".join(b for b in blocks if b) and r.n_chars == len(r.text)


@pytest.mark.parametrize(
    ("page", "text"),
    [
        (None, ""), ("", ""), ("<p", ""), ("plain", "plain"), ("<p>a &lt;b&gt;&nbsp; &amp;c</p>", "a <b> &c"),
        ("<article><h1>T</h1><p>a<br>b</p><aside>no</aside><p>c</p></article><div class='comments'><p>no no no</p></div>", "T\n\na b\n\nc"),
        ("<nav><a>x</a></nav><p>one</p><form>no</form><script>'<p>no</p>'</script><p>two</p><footer>no</footer>", "one\n\ntwo"),
        ("<div class='page-sidebar'><article><p>kept</p></article></div>", "kept"), ("<main>a<!-- b --><style>c</style>d</main>", "ad"),
        ("<article><p>one</p><div id=cookie-notice>no</div>two</article", "one\n\ntwo"),
        ("<div><p>the article</p><p>goes on</p></div><section class='comments'><article class='comment'><p>a reader</p></article></section>", "the article\n\ngoes on"),
        ("<article><p>one</p><p class='notice'>no<p>two<p>three</article>", "one\n\ntwo\n\nthree"), ("<article><p>one<p class=share>no<div>two</div><p>three</article>", "one\n\ntwo\n\nthree"),
        ("<div class='post-with-sidebar'><p>all of it</p></div>", "all of it"), ("<div class='l-sidebar-right'><p>all of it</p></div>", "all of it"),
        ("<main><p class='header'>Head</p><div class='search-results'><p>found</p></div></main>", "Head\n\nfound"), ("<div class='sidebar'><p>all there is</p></div>", "all there is"),
        ("<ul><li class=ad>no<li>one<li>two</ul>", "one\n\ntwo"), ("<table><tr><td class=advert>no<td>one<tr><td>two</table>", "one\n\ntwo"), ("<p>a</div></section>b<span class=share>c<span>d</span>e</span>f</p>", "abf"),
        ("<article><p>one</p><ul><li><a>a link</a><li><a>more</a><li><a>links</a></ul><p>two</p></article>", "one\n\ntwo"), ("<article><p>the text</p><div>Share this</div></article>", "the text"),
    ],
)
def test_pages(page, text):
    assert html_text.main_text(page) == text


def test_window_sums_and_spans_by_hand():
    rng = random.Random(8)
    for _ in range(300):
        w = [rng.choice([0, 0, 5, 30, 90]) for _ in range(rng.randint(0, 25))]
        sums = [sum(w[i : i + 3]) for i in range(len(w))]
        assert html_text.window_sums(w) == sums
        inside, now = [], False
        for i, s in enumerate(sums):
            now = s >= 20 if now else bool(w[i]) and s >= 80
            inside.append(now)
        assert [any(a <= i < b for a, b in html_text.spans(w, 80, 20)) for i in range(len(w))] == inside


def test_the_distribution_finds_the_article():
    """A page without marks, tags of prose or a named article: only the run of long lines is text."""
    say = lambda n: " ".join(f"w{i}" for i in range(n))
    short = "".join(f"<div><a>entry {i}</a></div>" for i in range(9))
    page = f"<div>Logo</div>{short}<div>{say(40)}</div><div>{say(60)}</div><div>{say(3)}</div><div>{say(50)}</div>{short}<div>all rights</div>"
    assert html_text.main_text(page) == "\n\n".join(say(n) for n in (40, 60, 3, 50))
    # inside a named article the same surge and dive cut what trails it
    assert html_text.main_text(f"<main><p>{say(40)}</p>{short}<div>by us</div><div></div><div></div></main>") == say(40)


def test_deep_pages_take_linear_time():
    n = 60_000
    assert html_text.main_text("<div>" * n + "deep" + "</section>" * n) == "deep"
    assert html_text.main_text("<p>" + "<div><p>x" * n).count("x") == n


def test_pages_odd(spark):
    df = spark.createDataFrame([(1, None, None, 1), (None, "u", "<p>x</p>", 2), (2, "u", "<b>" * 20_000 + "deep", None)], "page_id long, url string, html string, `text.n_chars` int").withColumn("text", F.lit("clash"))
    assert {r.page_id: r.text for r in html_text.extract(df).collect()} == {1: "", None: "x", 2: "deep"}
    assert html_text.extract(df.limit(0)).count() == 0


# --- urls ---------------------------------------------------------------------------------


def test_url_rules(spark):
    urls = {
        "https://WWW.Example.com/en/1": ("www.example.com", "/en/1", "www.example.com/en/", "allow"), "http://example.com/en/?q#f": ("example.com", "/en/", "example.com/en/", "block"),
        "http://a.net/fr/x": ("a.net", "/fr/x", "net/fr/", "block"), "http://a.net/fr": ("a.net", "/fr", None, None), "x://com/": ("com", "/", "com/", "allow"),
        "http://notcom/": ("notcom", "/", None, None), "http://a.com": ("a.com", "", None, None), "nothing": ("", "", None, None), None: ("", "", None, None),
    }
    df = spark.createDataFrame([(i, u) for i, u in enumerate(urls)], "page_id long, url string")
    got = by_id(url_filters.filter_urls(df), "page_id")
    for i, want in enumerate(urls.values()):
        r = got[i]
        assert (r.host, r.path, r.rule) == want[:3] and (r.verdict == want[3] if want[3] else r.verdict in ("allow", "block"))
    assert url_filters.filter_urls(df.limit(0)).count() == 0 and url_filters.filter_urls(df.union(df)).count() == 2 * len(urls)


RULED = (url_filters.UrlRule("allow", "good.org/news/"), url_filters.UrlRule("block", "bad.org/news/"), url_filters.UrlRule("allow", "mix.org/a/"), url_filters.UrlRule("allow", "mix.org/b/"), url_filters.UrlRule("block", "mix.org/c/"))


def filtered(spark, urls):
    return url_filters.filter_urls(spark.createDataFrame(list(enumerate(urls)), "page_id long, url string"), RULED)


def test_urls_follow_their_own_host(spark):
    """The same branch gets opposite verdicts on two hosts with opposite labels, and is left alone where nothing is known."""
    urls = [f"http://{h}.org/{b}/{i}" for h in ("good", "bad", "none") for b in ("news", "blog") for i in range(30)]
    got = filtered(spark, urls).where("path LIKE '/blog/%'").collect()
    assert {(r.host, r.verdict, r.template) for r in got} == {("good.org", "allow", "/blog/<*>"), ("bad.org", "block", "/blog/<*>"), ("none.org", "allow", "/blog/<*>")}
    assert {r.host: r.purity for r in got}["none.org"] == url_filters.BASE


def test_a_variable_middle_segment(spark):
    """Segments with many values are wildcards at any depth and do not part what follows; paths beyond the tree's depth are kept whole."""
    urls = [f"http://h.org/shop/item-{i}/{t}" for i in range(80) for t in ("reviews", "buy")] + [f"http://h.org/a/b/c/d/{x}/f" for x in ("e", "e", "g", "g")]
    got = Counter(r.template for r in filtered(spark, urls).collect())
    assert got == {"/shop/<*>/reviews": 80, "/shop/<*>/buy": 80, "/a/b/c/d/e/f": 2, "/a/b/c/d/g/f": 2}


def test_similar_branches_merge(spark):
    """Branches a and b are both allowed, c is blocked: two nodes, the first of two branches; purities by hand."""
    urls = [f"http://mix.org/{b}/{b}{i}" for b in "abc" for i in range(40)]  # no last segment occurs twice
    got = {(r.template, r.verdict, r.purity) for r in filtered(spark, urls).collect()}
    root = (80 + 4 * 0.5) / (120 + 4)
    up, down = (80 + 4 * root) / 84, 4 * root / 44
    assert got == {("/<+>/<*>", "allow", round((80 + 4 * up) / 84, 6)), ("/c/<*>", "block", round(4 * down / 44, 6))}


def test_urls_with_clashing_columns(spark):
    df = spark.createDataFrame([(1, "http://a.com/x", "h", 5, "z"), (None, None, None, None, None)], "page_id long, url string, host string, n long, `a.node` string")
    got = url_filters.filter_urls(df)
    assert got.count() == 2 and {r.verdict for r in got.collect()} == {"allow"}
