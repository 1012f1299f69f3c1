import hashlib
import re
import unicodedata
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from purchase_planner.functions import storage
from purchase_planner.llm import _text as tx
from purchase_planner.llm import bpe_lookup, curriculum, gif_media, html_layout, jaccard_regions, masked_lm, pii_disclosure, queries, subword_quality, syncmers, url_aliases
from purchase_planner.llm.components import components
from tests.conftest import SMALL

ODD = ["", " ", None, "a", "it's 'tis 'sx", "x" * 5000, "Ünï cödé 🎉 \n\n b", "same", "same", "don't\t\tstop  now \n"]
COLUMNS = "doc_id long, text string, lang string, source string, n_chars long, part string, body string, id long"


@pytest.fixture(scope="module")
def odd(spark):
    """Null and empty values, ties, repeated rows, and extra columns whose names clash with inner ones."""
    rows = [(i, t, "en", None if i % 3 else "s", len(t or ""), "p", "b", 7) for i, t in enumerate(ODD)]
    return spark.createDataFrame([*rows, rows[7]], COLUMNS)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], COLUMNS)


def test_syncmers(spark, odd, none):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    rows = sorted((r["doc_id"], r["text"]) for r in docs.select("doc_id", "text").collect())
    got = {r["doc_id"]: r for r in syncmers.edit_study(docs).collect()}
    for (d, t), (_, following) in zip(rows, rows[1:] + rows[:1], strict=True):
        h = len(t) // 2
        e = t[: len(t) - h] + following[:h]
        assert got[d]["n_chars"] == len(t) and got[d]["edited_sha256"] == hashlib.sha256(e.encode()).hexdigest()
        assert 0 <= got[d]["near_edited"] <= 1 and 0 <= got[d]["near_next"] <= 1
    same: dict[str, set] = {}
    for d, t in rows:
        same.setdefault(t, set()).add(got[d]["fingerprint"])
    assert all(len(s) == 1 for s in same.values())
    assert syncmers.edit_study(odd).count() == odd.count() and syncmers.edit_study(none).count() == 0
    assert syncmers.fingerprints(odd).where("n_chars = 0 and fingerprint <> ''").count() == 0


def test_syncmers_by_definition():
    text = "the quick brown fox jumps over the lazy dog and runs away"
    cps = np.array([ord(c) for c in text], np.uint32)
    k, s = 12, 5
    at, h = syncmers.anchors(cps, k, s)
    inner = syncmers._kmer_hashes(tx.mix(cps.astype(np.uint64) + np.uint64(0x632BE59BD9B4E019)), s)
    want = [i for i in range(len(text) - k + 1) if min(inner[i : i + k - s + 1]) in (inner[i], inner[i + k - s])]
    assert at.tolist() == want
    assert np.diff(at).max() <= k - s + 1
    moved, _ = syncmers.anchors(np.concatenate([cps[:3], cps]), k, s)
    assert {i + 3 for i in want} <= set(moved.tolist())
    f = (np.array([1, 5], np.uint64), np.array([0, 9]))
    back = syncmers.parsed(syncmers.text_of(f))
    assert back[0].tolist() == [1, 5] and back[1].tolist() == [0, 9] and syncmers.likeness(f, back, 4) == 1.0


def test_components(spark):
    edges = [(1, 2), (2, 3), (10, 11), (11, 12), (12, 10), (7, 7), (5, 9), (9, 1), (None, 4), (2, 3)]
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(edges, "src long, dst long")).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 5: 1, 9: 1, 10: 10, 11: 10, 12: 10, 7: 7}
    path = spark.createDataFrame([(i, i + 1) for i in range(40)], "src long, dst long")
    assert {r["component"] for r in components(path).collect()} == {0}
    assert components(spark.createDataFrame([], "src long, dst long")).count() == 0


def test_url_rules_and_aliases(spark):
    pages = [
        (1, "https://www.example.com/en/a", None), (2, "http://example.com/en/a?x=1", ""), (3, "https://b.net/es/x", '<link rel="canonical" href="https://c.org/y">'), (4, "http://c.org/y", None),
        (5, "http://c.org/z/", '<meta http-equiv="refresh" content="0; url=http://c.org/y">'), (6, None, None), (7, "no scheme", None), (8, "HTTP://EXAMPLE.com/fr/", None), (9, "http://free.org/", '<link rel=canonical href=http://sub.com/q>'),
    ]
    got = {r["page_id"]: r for r in url_aliases.judge(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    assert (got[1]["rule"], got[1]["verdict"]) == ("www.example.com/en/", "allow") and (got[2]["rule"], got[2]["verdict"]) == ("example.com/en/", "block")
    assert got[3]["verdict"] == got[4]["verdict"] == got[5]["verdict"] == "block" and got[4]["rule"] is None
    assert (got[6]["host"], got[6]["path"], got[6]["verdict"]) == ("", "", "allow") and got[7]["rule"] is None
    assert (got[8]["host"], got[8]["rule"]) == ("example.com", "com/") and got[9]["verdict"] == "allow"
    assert len(got) == 9 and url_aliases.judge(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_layout():
    text, blocks, items, cells = html_layout.render('<title>t</title><style>.x{display:none}</style>A<p>b<p>c<ul><li>d<li>e</ul><div class=x>no</div><table><tr><td>ab<td>c<tr><td>d<td>ef</table><pre> k\n l</pre><p hidden>no</p>')
    assert text == "A\n\nb\n\nc\n\n- d\n- e\n\nab | c\nd  | ef\n\n k\n l" and (items, cells) == (2, 4)
    assert html_layout.render("")[0] == "" and html_layout.render("a < b &amp; c")[0] == "a < b & c"
    assert html_layout.render("<div>" * 3000 + "deep")[0] == "deep"
    assert html_layout.render("<ol start=3><li>x<li>y</ol></p><script>no")[0].startswith("3. x\n4. y")


def test_layout_spans_and_visibility():
    render = lambda x: html_layout.render(x)[0]
    assert render("<table><tr><td rowspan=2>a<td>b<tr><td>c</table>") == "a | b\n  | c"
    assert render("<table><tr><td colspan=2>a<td>b<tr><td>1<td>2<td>3</table>") == "a |   | b\n1 | 2 | 3"
    assert render('<div style="visibility:hidden">x<b style="visibility:visible">y</b>z</div>') == "y"
    assert render('<style>p.a.b{display:none} .q{visibility:hidden}</style><p class="a b">no<p class="a">yes<p class=q>no') == "yes"
    assert render("hello <p class=x") == "hello" and render('<a href="x>y">t</a>') == "t"
    assert render("x<script>if(a<b){}</script >y") == "xy"


@pytest.mark.parametrize("unit", ["<a ", "<div>", "<div></span>", '<a href="', "<script></script ", "<li><b>", "<td><b></div>", "<p><b>"])
def test_layout_is_linear(unit):
    import time

    def seconds(n):
        began = time.process_time()
        html_layout.render("<div>" * n + unit * n)
        return time.process_time() - began

    seconds(500)
    assert seconds(16000) < 24 * max(seconds(2000), 0.01)


def test_layout_of_tables(spark, none):
    pages = spark.createDataFrame([(1, None, "x"), (2, "<p>a</p>", "x"), (2, "<p>a</p>", "x")], "page_id long, html string, text string")
    assert sorted((r["page_id"], r["text"]) for r in html_layout.texts(pages).collect()) == [(1, ""), (2, "a"), (2, "a")]
    assert html_layout.texts(pages.limit(0)).count() == 0


def _brute_groups(rows, words, percent):
    low = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    sets = {}
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(low))
        sets[i] = {tuple(w[k : k + words]) for k in range(len(w) - words + 1)} if len(w) >= words else {tuple(w)} - {()}
    label = {i: i for i in sets}

    def find(x):
        while label[x] != x:
            x = label[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                label[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in ids}


def _near_copies(rng, group, n, at, most):
    """Copies of one text of 60 words, each with up to `most` words replaced."""
    base = [f"{group}{x}" for x in rng.integers(0, 500, 60)]
    rows = []
    for i in range(n):
        w = list(base)
        for _ in range(int(rng.integers(0, most + 1))):
            w[int(rng.integers(0, len(w)))] = f"n{rng.integers(0, 40)}"
        rows.append((at + i, " ".join(w)))
    return rows


@pytest.mark.parametrize("local,members,chunk", [(1024, 256, 128), (6, 4, 3), (20, 16, 128)])
def test_jaccard_groups_against_brute_force(spark, monkeypatch, local, members, chunk):
    """Regions that recur in one task, and the same rows cut into Voronoi cells by Spark, level after level."""
    for name, value in (("LOCAL", local), ("MEMBERS", members), ("CHUNK", chunk), ("LEAF", 4)):
        monkeypatch.setattr(jaccard_regions, name, value)
    rng = np.random.default_rng(5)
    rows = [(i, t) for i, t in enumerate(ODD)]
    rows += _near_copies(rng, "w", 60, 100, 5) + _near_copies(rng, "v", 40, 200, 3)
    docs = spark.createDataFrame([(i, t, "x", 1) for i, t in rows], "doc_id long, text string, part string, id long")
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_regions.groups(docs, words=4, percent=85).collect()}
    assert got == _brute_groups(rows, 4, 85)


@pytest.mark.parametrize("percent", [50, 80, 85])
@pytest.mark.parametrize("drift", [0.05, 0.1, 0.3])
def test_voronoi_recursion_in_memory(percent, drift):
    """Chains, tight clusters and sets at like distances: the links found join what brute force joins."""
    rng = np.random.default_rng(int(percent * 10 + drift * 100))
    parts, pool = [], rng.integers(1, 1 << 62, 4000, dtype=np.uint64)
    for _ in range(6):
        now = rng.choice(pool, 60, replace=False)
        for _ in range(50):
            if rng.random() < 0.3:
                now = np.concatenate([now[rng.random(len(now)) > drift], rng.choice(pool, max(1, int(60 * drift)))])
            near = np.concatenate([now[rng.random(len(now)) > drift / 2], rng.choice(pool, 1)])
            parts.append(np.unique(near).tobytes())
    sets = [set(np.frombuffer(p, np.uint64).tolist()) for p in parts]

    def joined(links):
        label = np.arange(len(sets))
        for a, b in links:
            label[label == label[b]] = label[a]
        return {frozenset(np.flatnonzero(label == x).tolist()) for x in set(label.tolist())}

    want = [(a, b) for a in range(len(sets)) for b in range(a) if 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])]
    got = jaccard_regions.solve(jaccard_regions.Sets(parts), np.arange(len(sets)), percent, np.random.default_rng(1))
    assert set(map(lambda p: (max(p), min(p)), got)) <= set(want)
    assert joined(got) == joined(want)


@pytest.mark.parametrize("local", [1024, 30])
def test_jaccard_link_across_pivots(spark, monkeypatch, local):
    """Groups whose sets all lie near their own pivot, joined by one pair of two that are no pivots."""
    monkeypatch.setattr(jaccard_regions, "LOCAL", local)
    core = [f"c{i}" for i in range(100)]
    group = lambda x, at, n: [(at + i, " ".join([*core, *(f"{x}{k}" for k in range(10)), f"{x}own{i}"])) for i in range(n)]
    between = [(300, " ".join([*core, *(f"a{k}" for k in range(10)), *(f"b{k}" for k in range(2))])), (301, " ".join([*core, *(f"b{k}" for k in range(10)), *(f"a{k}" for k in range(2))]))]
    rows = [*group("a", 0, 80), *group("b", 100, 80)]
    assert len({c for _, c in _brute_groups(rows, 1, 85).values()}) == 2
    rows += between
    want = _brute_groups(rows, 1, 85)
    assert len({c for _, c in want.values()}) == 1
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_regions.groups(docs, words=1, percent=85).collect()} == want


def test_jaccard_edges(spark, odd, none):
    assert jaccard_regions.groups(none).count() == 0
    kept = jaccard_regions.deduplicated(odd)
    assert kept.columns == odd.columns and kept.where("text = 'same'").count() == 1
    nulls = spark.createDataFrame([(None, "a b c d e f"), (3, "a b c d e f"), (None, None)], "doc_id long, text string")
    assert jaccard_regions.groups(nulls).count() == 3


def test_link_targets(spark):
    cases = [
        ("http://a.com/x/y?q=1", "/p", "http://a.com/p"), ("http://a.com/x/y", "p.html", "http://a.com/x/p.html"), ("https://a.com", "p", "https://a.com/p"),
        ("http://a.com/x/y", "//b.net/es/1", "http://b.net/es/1"), ("http://a.com/x/y/z", "../p", "http://a.com/x/p"), ("http://a.com/x", "?b=2", "http://a.com/x?b=2"),
        ("http://a.com/x", "#top", None), ("http://a.com/x", "mailto:a@b.c", None), ("http://a.com/x", "https://c.org/?a=1&amp;b=2", "https://c.org/?a=1&b=2"), ("nowhere", "/p", None),
    ]
    df = spark.createDataFrame(cases, "base string, ref string, want string")
    got = df.withColumn("got", url_aliases.resolved(F.col("base"), url_aliases.decoded(F.col("ref")))).collect()
    assert [r["got"] for r in got] == [r["want"] for r in got]
    html = '<base href="http://q.net/es/"><link rel="canonical" href=\'1\'><meta http-equiv=refresh content="0; url=/fr/2">'
    pages = spark.createDataFrame([(1, "http://a.org/x", html), (2, "http://b.org/x", None), (3, None, html)], "page_id long, url string, html string")
    edges = {tuple(r) for r in url_aliases.link_edges(pages).collect()}
    assert edges == {("http://a.org/x", "http://q.net/es/1"), ("http://a.org/x", "http://q.net/fr/2")}


def test_chains_and_hubs_of_links(spark):
    """A long chain ends in a blocked address, a hub's spokes hold one allowed address, and a lone page has neither."""
    chain = [(f"http://c{i}.org/x", f"http://c{i + 1}.org/x") for i in range(60)] + [("http://c60.org/x", "http://k.net/es/1")]
    hub = [(f"http://h{i}.org/x", "http://hub.org/y") for i in range(200)] + [("http://hub.org/y", "http://k.net/fr/9"), ("http://h7.org/x", "http://good.com/z")]
    urls = ["http://c0.org/x", "http://c30.org/x", "http://h150.org/x", "http://hub.org/y", "http://lone.org/"]
    pages = spark.createDataFrame([(i, u, None, 5) for i, u in enumerate(urls)], "page_id long, url string, html string, host int")
    links = spark.createDataFrame(chain + hub, "src string, dst string")
    got = {r["page_id"]: r["verdict"] for r in url_aliases.judge(pages, redirects=links).collect()}
    assert got == {0: "block", 1: "block", 2: "allow", 3: "allow", 4: "allow"}
    assert {r["verdict"] for r in url_aliases.judge(pages, redirects=links.limit(0), default="block").collect()} == {"block"}


def test_quality_on_held_out_labels(spark):
    """Ranking of labels that training never sees, and scores of columns with inner names."""
    d = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    model = subword_quality.train(docs, labels, ~subword_quality.held_out())
    scored = subword_quality.score(docs, model).join(labels.where(subword_quality.held_out()), "doc_id").select("score", "quality").toPandas()
    good, bad = scored[scored["quality"] == 1]["score"].to_numpy(), scored[scored["quality"] == 0]["score"].to_numpy()
    assert len(good) > 20 and len(bad) > 5
    assert (good[:, None] > bad[None, :]).mean() > 0.95
    odd = docs.limit(5).withColumn("score", F.lit(7)).withColumn("__body", F.lit("b")).withColumn("__score", F.lit(1.0))
    assert subword_quality.accepted(odd, model, 0.0).columns == odd.columns and subword_quality.accepted(odd, model, 0.0).count() == 5


def test_quality_grams_are_characters():
    texts = ["Ünï", "U"]
    for t in texts:
        raw = np.frombuffer(t.encode(), np.uint8)
        _, counts = subword_quality.word_features(raw, np.array([0]), np.array([len(raw)]))
        assert counts[0] == 1 + sum(max(len(t) + 2 + 1 - g, 0) for g in subword_quality.GRAMS)


INNER = "key base body terms entries d t rows score place tie copy size before source_size label region id n part s f1 f2 rep lone".split()


def test_stages_with_columns_of_inner_names(spark):
    """Columns named as the stages' own, nulls, a text of a megabyte, repeated rows and no rows at all."""
    rows = [(i, t, "en", None if i % 2 else "s", len(t or "")) for i, t in enumerate(["a b c d e f", None, "", "same text of a few words here", "same text of a few words here", "x y " * 250_000, "call a@b.org now"])]
    docs = spark.createDataFrame([*rows, rows[0], rows[0]], "doc_id long, text string, lang string, source string, n_chars long")
    docs = docs.select("*", *[F.lit(k).alias(c) for k, c in enumerate(INNER)])
    model = subword_quality.Model(np.zeros(subword_quality.BUCKETS), 0.0)
    stages = {"quality": lambda x: subword_quality.accepted(x, model, 0.3), "near": jaccard_regions.deduplicated, "private": pii_disclosure.sanitised, "mix": curriculum.mixed}
    for name, f in stages.items():
        out = f(docs)
        assert out.columns == docs.columns, name
        got = out.collect()
        assert all(r[c] == k for r in got for k, c in enumerate(INNER)), name
        if name in ("quality", "private"):
            assert len(got) == docs.count()
        if name == "near":
            assert len(got) == 6
        if name == "mix":
            per = curriculum.plan(docs).toPandas()
            assert sum(len((r["text"] or "").split()) for r in got) == per["taken"].sum()
        assert f(docs.limit(0)).count() == 0, name


def test_mix(spark, odd, none):
    plan = curriculum.plan(odd).toPandas()
    assert len(plan) == odd.count() and (plan["taken"] <= 2 * plan["size"]).all()
    for _, g in plan.groupby(plan["source"].fillna("?")):
        assert g["taken"].sum() == int(g["target"].iloc[0])
    assert plan.groupby("source", dropna=False)["target"].first().sum() == pytest.approx(1.5 * plan["size"].sum())
    assert curriculum.plan(none).count() == 0
    mix = curriculum.mixed(odd)
    assert mix.columns == odd.columns
    words = mix.select(curriculum.n_words(F.col("text")).alias("w")).agg(F.sum("w")).first()[0]
    assert words == plan["taken"].sum()


def test_positions_invert_demand(spark):
    df = spark.createDataFrame([(i / 10, s) for i in range(11) for s in (0.8, 0.0, -0.8)], "done double, slope double")
    t = F.col("t")
    got = df.withColumn("t", curriculum.position(F.col("done"), F.col("slope"))).withColumn("back", t + F.col("slope") * (t * t - t))
    assert got.where(F.abs(F.col("back") - F.col("done")) > 1e-9).count() == 0


def _gif(frames, palette, screen):
    out = b"GIF89a" + screen[0].to_bytes(2, "little") + screen[1].to_bytes(2, "little") + bytes([0x80 | 7, 0, 0]) + palette
    for (left, top, w, h), pixels, disposal, transparent in frames:
        out += b"\x21\xf9\x04" + bytes([disposal << 2 | (transparent is not None), 5, 0, transparent or 0]) + b"\0"
        out += b"\x2c" + b"".join(x.to_bytes(2, "little") for x in (left, top, w, h)) + b"\0\x08"
        stream = gif_media.pack_codes(gif_media.lzw_codes(bytes(pixels)))
        out += b"".join(bytes([len(stream[i : i + 200])]) + stream[i : i + 200] for i in range(0, len(stream), 200)) + b"\0"
    return out + b"\x3b"


def test_gif_disposal_and_transparency():
    palette = bytes(np.stack([np.arange(256), np.zeros(256), 255 - np.arange(256)], 1).astype(np.uint8))
    media = _gif([((0, 0, 2, 2), [1, 2, 3, 4], 1, None), ((1, 0, 1, 2), [9, 5], 2, 5), ((0, 1, 1, 1), [7], 3, None), ((0, 0, 1, 1), [8], 1, None)], palette, (2, 2))
    shown = [f.canvas[:, :, 0].tolist() for f in gif_media.read_gif(media)]
    assert shown == [[[1, 2], [3, 4]], [[1, 9], [3, 4]], [[1, 0], [7, 0]], [[8, 0], [3, 0]]]
    assert gif_media.read_gif(media)[0].canvas[0, 0].tolist() == [1, 0, 254]
    with pytest.raises(ValueError):
        gif_media.read_gif(media[:40])
    with pytest.raises(ValueError):
        gif_media.read_gif(b"nothing")


@pytest.mark.parametrize("data", [bytes(64), bytes(range(256)) * 64, b"ab" * 40000, np.random.default_rng(1).bytes(64 * 3000)])
def test_gif_round_trip(data):
    assert b"".join(f.indices.tobytes() for f in gif_media.read_gif(gif_media.write_gif(data))) == data


def test_gif_queries(spark, odd, none):
    got = gif_media.digest(odd).toPandas()
    for d, h, n in zip(got["doc_id"], got["payload_sha256"], got["n_bytes"], strict=True):
        raw = (ODD[d] or "").encode()
        assert n == len(raw) and h == hashlib.sha256(raw + bytes(-len(raw) % 64 if raw else 64)).hexdigest()
    media = gif_media.frames(gif_media.store_texts(odd))
    first = media.where("doc_id = 3").first()["frames"][0]
    assert first["samples"][:1] == b"a" and sum(first["colour_histogram"]) == 64
    assert gif_media.digest(none).count() == 0


def test_quality(spark, odd, none):
    docs, labels = spark.read.parquet(f"{SMALL}/documents.parquet"), spark.read.parquet(f"{SMALL}/labels.parquet")
    model = subword_quality.train(docs, labels, ~subword_quality.held_out())
    got = subword_quality.score(docs, model).join(labels, "doc_id").toPandas()
    assert ((got["score"] >= 0.3) == got["quality"]).mean() > 0.9
    assert subword_quality.score(odd, model).where("score between 0 and 1").count() == odd.count()
    assert subword_quality.score(none, model).count() == 0
    empty = subword_quality.train(none, labels, F.lit(True))
    assert subword_quality.score(odd, empty).where("score = 0.5").count() == odd.count()


def test_bpe_against_the_library(spark, odd, none):
    import public_tokenizers as P
    import tiktoken

    path = queries.tokenizer_path()
    v = bpe_lookup.vocabulary_of(path)
    assert sorted(v.find(tx.span_hashes(v.data, v.id_start, v.id_start + v.id_length)).tolist()) == list(range(len(v.ranks)))  # minimal and perfect
    library = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=v.ranks, special_tokens={})
    more = ["a\r\n's", "'S 'LL", "a  '", "\x1c\x1d x", "日本語 テスト", " 's", "ab" * 900, "1234 ½ Ⅷ", " " * 50 + "b"]
    texts = [t or "" for t in ODD] + more + [r["text"] for r in spark.read.parquet(f"{SMALL}/documents.parquet").select("text").collect()]
    got = []
    for _, _, data, offsets in tx.each_slice(pa.array(texts)):
        ids, where = bpe_lookup.encode_slice(v, data, offsets)
        got += [ids[a:b].tolist() for a, b in zip(where[:-1], where[1:], strict=True)]
    assert got == [library.encode_ordinary(t) for t in texts]
    rows = bpe_lookup.round_trip(spark, odd, path).toPandas()
    assert all(h == hashlib.sha256((ODD[d] or "").encode()).hexdigest() for d, h in zip(rows["doc_id"], rows["decoded_sha256"], strict=True))
    assert bpe_lookup.round_trip(spark, none, path).count() == 0
    back = bpe_lookup.decode(spark, bpe_lookup.encode(spark, odd, path), path).toPandas()
    assert all(b == (ODD[d] or "").encode() for d, b in zip(back["doc_id"], back["bytes"], strict=True))


def test_bpe_memory_is_fixed(monkeypatch):
    v = bpe_lookup.Vocabulary.read(queries.tokenizer_path())
    size = lambda: sum(a.nbytes for a in (v.memo.one, v.memo.two, v.memo.count, v.memo.ids))
    whole = size()
    assert whole < 30e6
    monkeypatch.setattr(bpe_lookup, "MEMO", 64)  # slots are taken over
    v.memo, lengths = bpe_lookup.Memo(), []
    before = size()
    texts = [f"q{i * 7919 % 5000:x}zx{i % 91}w" + "xqz" * (i % 9) for i in range(6000)]
    for i, j, data, offsets in tx.each_slice(pa.array(texts * 2), 1 << 14):
        lengths.append(len(data))
        ids, where = bpe_lookup.encode_slice(v, data, offsets)
        back, each = v.text_bytes(ids)
        upto = np.append(0, np.cumsum(each))[where]
        assert [back.tobytes()[a:b].decode() for a, b in zip(upto[:-1], upto[1:], strict=True)] == (texts * 2)[i:j]
        alone = bpe_lookup.Vocabulary.__new__(bpe_lookup.Vocabulary)
        alone.__setstate__({**v.__getstate__()})
        assert np.array_equal(ids, bpe_lookup.encode_slice(alone, data, offsets)[0])
    assert max(lengths) <= 1 << 14 and size() == before
    assert np.array_equal(np.concatenate([bpe_lookup.heap_merge(x, v.ranks) for x in (b"qzxqzx", b"zxw")]), np.concatenate([bpe_lookup.encode_slice(v, np.frombuffer(x, np.uint8), np.array([0, len(x)]))[0] for x in (b"qzxqzx", b"zxw")]))


def test_masked_lm_by_hand(spark, odd, none):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    lex = masked_lm.lexicon(masked_lm.word_counts(docs))
    net = masked_lm.train(docs, lex)
    got = {r["doc_id"]: r for r in masked_lm.score(odd, lex, net).collect()}
    assert got[2]["n_tokens"] == 0 and got[2]["pseudo_log_likelihood"] == 0 and got[2]["mean"] is None
    text = next(t for t in ODD if t and "stop" in t)
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    data = np.frombuffer(" ".join(words).encode(), np.uint8)
    starts, ends, _ = tx.words(data, np.array([0, len(data)]))
    tokens = lex.encode(tx.span_hashes(data, starts, ends)).tolist()
    total = 0.0
    for i, t in enumerate(tokens):
        near = [tokens[i + d] if 0 <= i + d < len(tokens) else 0 for d in (-2, -1, 1, 2)]
        hidden = np.tanh(np.concatenate([net.embedding[x] for x in near]) @ net.inner + net.bias)
        z = hidden @ net.outer + net.prior
        total += z[lex.classes[t]] - np.log(np.exp(z).sum()) + lex.within[t]
    assert got[ODD.index(text)]["pseudo_log_likelihood"] == pytest.approx(total, abs=1e-3)
    before = sum(r["pseudo_log_likelihood"] for r in masked_lm.score(docs, lex, masked_lm.start()).collect())
    after = sum(r["pseudo_log_likelihood"] for r in masked_lm.score(docs, lex, net).collect())
    assert after > before and masked_lm.score(none, lex, net).count() == 0


def _brute_spans(t):
    patterns = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}
    out = []
    for kind, p in patterns.items():
        for m in re.finditer(p, t):
            d = re.sub("[^0-9]", "", m[0])
            luhn = sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(reversed(d))) % 10 == 0
            if {"email": True, "ip": kind == "ip" and all(int(x) < 256 for x in m[0].split(".")), "card": 13 <= len(d) <= 19 and luhn, "phone": 9 <= len(d) <= 15}[kind]:
                out.append(f"{kind}:{m.start()}:{m.end()}")
    return ",".join(out)


PII = ["é a@b.c_d@e.fg x", "1.2.3.4.5.6.7.8 256.1.1.1 001.02.3.4", "4111 1111 1111 1111 and 4111-1111-1111-1112", "+1 (555) 123-4567 +12", "a@b", "x@y.zz " * 300, "1" * 3000, "+1 4111111111111111", "9.9.9.9.", "a.b@c.d.e-f, 12-4111 1111 1111 1111", "..@..@a.b.c@d.e"]


def test_pii_spans(spark, odd, none):
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(PII)], "doc_id long, text string")
    got = {r["doc_id"]: r for r in pii_disclosure.report(docs).collect()}
    for i, t in enumerate(PII):
        assert got[i]["base_sha256"] == hashlib.sha256(_brute_spans(t).encode()).hexdigest(), t
    assert pii_disclosure.report(odd).where("n_email + n_ip + n_card + n_phone = 0").count() == odd.count()
    assert pii_disclosure.report(none).count() == 0


def test_disclosure(spark):
    rows = [(i, f"common words here zebrafish {'a@b.org' if i < 3 else 'nothing'} common place number{i}") for i in range(40)]
    rows = [(i, t if i < 3 else t.replace("zebrafish", "plain")) for i, t in rows]
    docs = spark.createDataFrame([(i, t, len(t)) for i, t in rows], "doc_id long, text string, n_chars long")
    spans = {r["doc_id"]: r["spans"] for r in pii_disclosure.report(docs).collect()}
    word = lambda i, s: rows[i][1][int(s.split(":")[1]) : int(s.split(":")[2])]
    found = {word(0, s) for s in spans[0].split(",") if s.startswith("term")}
    assert "zebrafish" in found and "common" not in found and spans[20] == ""
    clean = {r["doc_id"]: r for r in pii_disclosure.sanitised(docs).collect()}
    assert clean[20]["text"] == rows[20][1] and "[EMAIL]" in clean[0]["text"] and "zebrafish" not in clean[0]["text"]
    assert clean[0]["n_chars"] == len(clean[0]["text"])
    assert pii_disclosure.sanitised(docs).columns == docs.columns


def test_word_count_and_checksums(spark):
    df = spark.createDataFrame([("a b c\td\x0be",), ("",), (None,)], "t string")
    assert [r[0] for r in df.select(curriculum.n_words(F.col("t"))).collect()] == [len(re.findall(r"[^\x20\x09-\x0D]+", "a b c\td\x0be")), 0, 0]
    assert spark.range(10).where(subword_quality.held_out("id")).count() == sum(zlib.crc32(str(i).encode()) % 5 == 0 for i in range(10))
    assert unicodedata.category("a")[0] == "L"


def test_intermediate_tables_are_dropped(spark, odd, monkeypatch, tmp_path):
    monkeypatch.setattr(storage, "folder", lambda _: f"file://{tmp_path}")
    for f, kept in ((jaccard_regions.deduplicated, 3), (curriculum.mixed, 1), (pii_disclosure.sanitised, 1)):
        before = set(tmp_path.glob("table-*"))
        out = f(odd)
        assert len(set(tmp_path.glob("table-*")) - before) <= kept, f
        assert out.columns == odd.columns and out.count() > 0
    before = set(tmp_path.glob("table-*"))

    def fails():
        storage.settle(odd)
        raise ValueError

    with pytest.raises(ValueError):
        storage.settle_last(fails)
    assert set(tmp_path.glob("table-*")) == before
