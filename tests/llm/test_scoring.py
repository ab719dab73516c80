"""Mixing, quality, fingerprints, main text and the pipeline."""

import hashlib
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from bitplane.llm import ctph, mixing, quality, queries, wrapper

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
EDGE = [(1, None, None, None, None), (2, "", "en", "a", 0), (3, "word " * 50000, "en", "a", 250000), (4, "same text", "de", "b", 9), (4, "same text", "de", "b", 9), (None, "no id", "de", "b", 5), (6, "\n\t ", None, "b", None)]


def edge(spark, rows=EDGE):
    return spark.createDataFrame([(*r, "clash", 0.5) for r in rows], DOCS + ", probability string, target double")


def test_raking_meets_its_margins(spark):
    rnd = random.Random(4)
    rows = [(i, " ".join(f"w{rnd.randint(0, 99)}" for _ in range(rnd.randint(5, 60))), rnd.choice(["en", "en", "de"]), rnd.choice(["a", "a", "a", "b", "c"]), 1) for i in range(600)]
    df = spark.createDataFrame(rows, DOCS)
    words = mixing.anchors(df, 4, most_share=0.9, sizes=(2, 3))
    held = {w: sum(w in r[1].split() for r in rows) for w in {w for r in rows for w in r[1].split()}}
    assert words == sorted(sorted((w for w in held if held[w] <= 540 and 2 <= len(w) <= 3), key=lambda w: (-held[w], w))[:4], key=lambda w: (held[w], [-ord(c) for c in w]))
    tagged = mixing.features(df, words)
    for r in tagged.collect():
        own = r.text.split()
        assert r["__tokens"] == len(own) and r["__topic"] == next((k + 1 for k, w in enumerate(words) if w in own), 0)
    cells = mixing.stored(mixing.cells_of(tagged), "cells")
    wanted = {m: mixing.targets(cells, m, 0.5) for m in mixing.MARGINS}
    raked = mixing.rake(cells, wanted, 12)
    for m in mixing.MARGINS:
        got = {r[0]: r[1] for r in raked.groupBy(m).sum("raked").collect()}
        for value, target in wanted[m].collect():
            assert got[value] == pytest.approx(target, abs=1e-4)
    out = mixing.weigh(df, share=0.5, topics=4).collect()
    total = sum(r["__tokens"] for r in out)
    assert sum(r["__tokens"] * r["__probability"] for r in out) == pytest.approx(total / 2, rel=1e-3)
    assert sum(r["__tokens"] for r in out if r["__selected"]) == pytest.approx(total / 2, rel=0.2)


def test_mixing_to_the_callers_targets(spark):
    rnd = random.Random(14)
    rows = [(i, " ".join(rnd.choices(["alpha", "beta"], k=20)), rnd.choice(["en", "de"]), rnd.choice("aab"), 1, rnd.choice(["x", "y", None])) for i in range(900)]
    df = spark.createDataFrame(rows, DOCS + ", kind string")
    wanted = {"source": {"a": 1, "b": 3, "absent": 5}, "lang": {"en": 0.9, "de": 0.1}, "topic": {"x": 1, "y": 1, "(none)": 2}}
    out = mixing.weigh(df, share=0.05, wanted=wanted, topic_col="kind", rounds=20).collect()
    mass = lambda m, v: sum(r["__tokens"] * r["__probability"] for r in out if r[f"__{m}"] == v)
    total = sum(r["__tokens"] * r["__probability"] for r in out)
    assert total == pytest.approx(0.05 * sum(r["__tokens"] for r in out), rel=1e-3)
    assert mass("source", "b") / total == pytest.approx(0.75, abs=0.01) and mass("lang", "en") / total == pytest.approx(0.9, abs=0.01) and mass("topic", "(none)") / total == pytest.approx(0.5, abs=0.01)
    none = mixing.weigh(df, wanted={"source": {"b": 1}}, topic_col="kind").collect()
    assert all(r["__probability"] == 0 for r in none if r["__source"] == "a")
    twice = mixing.weigh(df.unionByName(df), share=0.05, wanted=wanted, topic_col="kind", rounds=20).collect()
    fates = {}
    for r in twice:
        fates.setdefault(r.doc_id, set()).add((r["__probability"], r["__selected"]))
    assert all(len(f) == 1 for f in fates.values())


def test_mixing_edges(spark):
    out = mixing.weigh(edge(spark))
    got = {r.doc_id: r for r in out.collect()}
    assert got[1]["__source"] == "(none)" and got[2]["__tokens"] == 0 and not got[2]["__selected"] and not got[6]["__selected"]
    assert mixing.mix(edge(spark)).columns == edge(spark).columns
    assert mixing.weigh(edge(spark, [])).collect() == [] and mixing.mix(edge(spark, [])).collect() == []


def test_quality_held_out_accuracy(spark, small):
    docs, labels = (spark.read.parquet(f"{small.replace('0.001', '0.01')}/{t}.parquet") for t in ("documents", "labels"))
    train, test = labels.where("doc_id % 3 > 0"), labels.where("doc_id % 3 = 0")
    scored = quality.classify(docs, train).join(test, "doc_id")
    bad, good = scored.where("quality = 0"), scored.where("quality = 1")
    assert good.where("kept").count() >= 0.97 * good.count()
    assert bad.where("not kept").count() >= 0.8 * bad.count()


def test_quality_edges(spark, small):
    docs, labels = (spark.read.parquet(f"{small}/{t}.parquet") for t in ("documents", "labels"))
    model = quality.fit(quality.prepared(docs), labels)
    assert model is not None and 0.05 <= model.cut <= 0.5 and 1 <= len(model.rounds) <= 3
    assert quality.score(edge(spark), model).count() == len(EDGE)
    assert quality.keep_good(edge(spark), labels.where("quality = 1")).count() == len(EDGE)
    assert quality.score(edge(spark), None).where("kept").count() == len(EDGE)
    assert quality.score(edge(spark, []), model).collect() == []
    kept = quality.keep_good(docs, labels)
    assert kept.columns == docs.columns and kept.count() == quality.score(docs, model).where("kept").count()
    nulls = labels.unionByName(spark.createDataFrame([(None, 1, 0), (10**9, None, 0), (5, 7, 0)], "doc_id long, quality int, toxic int"))
    assert quality.fit(quality.prepared(docs), nulls).cut == model.cut


def test_quality_learns_from_all_documents(spark, small):
    docs, labels = (spark.read.parquet(f"{small.replace('0.001', '0.01')}/{t}.parquet") for t in ("documents", "labels"))
    more = docs.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(5)))).withColumn("doc_id", F.col("doc_id") + F.col("copy") * 10**8)
    model = quality.fit(quality.prepared(more), labels)
    assert model.rounds[-1][0] > 5 * docs.count() * 0.5 > 2000
    again = quality.fit(quality.prepared(more.repartition(3, "doc_id")), labels)
    assert again.rounds == model.rounds and abs(again.cut - model.cut) < 1e-6 and abs(again.weights.grams - model.weights.grams).max() < 1e-4


def made(rnd, n, first=0):
    """Documents whose source and whose words both tell their class, mostly and independently."""
    rows = []
    for i in range(first, first + n):
        good = rnd.random() < 0.6
        words = rnd.choices(["river", "house", "green", "walk"] if (rnd.random() < 0.9) == good else ["zzxq", "$$$", "qqj", "##"], k=40)
        rows.append((i, " ".join(words + rnd.choices("abcdefgh", k=10)), "en", rnd.choice("abc" if (rnd.random() < 0.97) == good else "xyz"), 300, int(good)))
    return rows


def test_views_are_separate_and_teach_each_other(spark):
    rnd = random.Random(11)
    rows = made(rnd, 3000)
    docs = spark.createDataFrame([r[:5] for r in rows], DOCS)
    labels = spark.createDataFrame([(r[0], r[5]) for r in rows[:600]], "doc_id long, quality int")
    model = quality.fit(quality.prepared(docs), labels, sure=0.9)
    assert all(n > 900 for pair in model.rounds for n in pair)
    texts, fields = [r[1] for r in rows], [(r[3], r[2], r[4]) for r in rows]
    y = np.array([r[5] for r in rows[600:]])

    def auc(p):
        order = np.argsort(np.argsort(p[600:]))
        return (order[y == 1].mean() - (y.sum() - 1) / 2) / (len(y) - y.sum())

    a, b, joint = model.score(texts, fields)
    assert auc(a) > 0.8 and auc(b) > 0.9 and auc(joint) > max(auc(a), auc(b))
    assert np.array_equal(model.score(texts, [("a", "en", 300)] * len(rows))[0], a)  # content does not see fields
    assert np.array_equal(model.score(["other"] * len(rows), fields)[1], b)  # metadata does not see text


def test_cut_stands_flipped_labels(spark, small):
    docs, labels = (spark.read.parquet(f"{small.replace('0.001', '0.1')}/{t}.parquet") for t in ("documents", "labels"))
    flipped = labels.withColumn("quality", F.when(F.pmod(F.xxhash64("doc_id", F.lit(1)), F.lit(200)) == 0, 1 - F.col("quality")).otherwise(F.col("quality")))
    straight, odd = (quality.classify(docs, x).select("doc_id", "kept") for x in (labels, flipped))
    both = labels.join(straight, "doc_id").join(odd.withColumnRenamed("kept", "odd"), "doc_id")
    bad, good = both.where("quality = 0"), both.where("quality = 1")
    assert bad.where("not kept").count() >= 0.9 * bad.count() and bad.where("not odd").count() >= 0.85 * bad.count()
    assert good.where("odd").count() >= 0.99 * good.count()


def test_pool_counts_add_up(spark, small):
    docs = quality.prepared(spark.read.parquet(f"{small}/documents.parquet")).where("length(text) > 0")
    ids = sorted(r.doc_id for r in docs.select("doc_id").collect())
    known, rest = np.array(ids[::4]), spark.createDataFrame([(i,) for k, i in enumerate(ids) if k % 4], "doc_id long")
    s = quality.sample_features(docs, rest)
    rnd = np.random.default_rng(3)
    w = quality.Weights(*(rnd.normal(size=n) for n in (quality.DIMS, quality.SLOTS, quality.SLOTS)))
    content_cal, meta_cal = np.array([3.0, 0.1, 0.0]), np.array([0.5, 0.0])
    got = quality.pool_counts(docs.repartition(5), known, w, content_cal, meta_cal, 0.6)
    a, b = s.scores(w)
    want = s.counts(quality.classes_of(quality.prob(meta_cal, b), 0.6), quality.classes_of(quality.prob(content_cal, a), 0.6))
    assert got.n_meta.min() > 0 < got.n_content.min() and np.allclose(got.grams, want.grams, atol=1e-4)
    assert (got.meta == want.meta).all() and (got.layout == want.layout).all() and (got.n_content == want.n_content).all() and (got.n_meta == want.n_meta).all()


def test_fingerprints():
    rnd = random.Random(1)
    base = "".join(rnd.choices("abcdefgh \n", k=9000))
    near = base[:4000] + "EDIT" + base[4004:]
    far = "".join(rnd.choices("abcdefgh \n", k=9000))
    f, g, h, e, e2 = ctph.fingerprints([base, near, far, "", base])
    assert f == e2 and e == "3::" and ctph.likeness(f, f) == 1.0
    assert ctph.likeness(f, g) > 0.9 and ctph.likeness(f, h) == 0.0 and ctph.likeness(f, e) == 0.0
    assert ctph.likeness(f, ctph.fingerprints([base * 2])[0]) > 0
    assert ctph.common_length("abcbdab", "bdcaba") == 4 and ctph.common_length("", "a") == 0
    assert ctph.fingerprints(["x" + base, far])[0] == ctph.fingerprints(["x" + base])[0]


def plain_fingerprint(text):
    """The fingerprint byte by byte: a rolling hash of seven bytes, one digit a piece."""
    raw = text.encode()

    def pieces(size, most):
        out, start, window = "", 0, [0] * 7
        for at, byte in enumerate(raw):
            window = window[1:] + [byte]
            total = sum(window) + sum((k + 1) * b for k, b in enumerate(window))
            shifted = 0
            for b in window:
                shifted = (shifted << 5 ^ b) & 0xFFFFFFFF
            if ((total + shifted) % 2**32 + 1) % size == 0 and len(out) < most - 1:
                out += ctph.DIGITS[(zlib.crc32(raw[start : at + 1]) * 0x9E3779B1 >> 20) & 63]
                start = at + 1
        return out + (ctph.DIGITS[(zlib.crc32(raw[start:]) * 0x9E3779B1 >> 20) & 63] if start < len(raw) else "")

    size = 3
    while size * 64 < len(raw):
        size *= 2
    while size > 3 and len(pieces(size, 10**9)) - (len(raw) > 0) < 32:
        size //= 2
    return f"{size}:{pieces(size, 64)}:{pieces(2 * size, 32)}" if raw else "3::"


def edit_distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a):
        new = [i + 1]
        for j, y in enumerate(b):
            new.append(row[j] if x == y else 1 + min(row[j + 1], new[j]))
        row = new
    return row[-1]


def test_fingerprints_against_a_plain_rolling_hash():
    rnd = random.Random(17)
    texts = ["", "a", "abc" * 5, "é中😀" * 30] + ["".join(rnd.choices("abcdefgh \n.,é", k=rnd.randint(1, 6000))) for _ in range(60)]
    assert ctph.fingerprints(texts) == [plain_fingerprint(t) for t in texts]
    for _ in range(200):
        a, b = ("".join(rnd.choices("abcd", k=rnd.randint(1, 60))) for _ in "xy")
        assert len(a) + len(b) - 2 * ctph.common_length(a, b) == edit_distance(a, b)


@pytest.mark.parametrize("rows", [EDGE, EDGE[:1], []])
def test_fingerprint_neighbours(spark, rows):
    order = sorted(rows, key=lambda r: (r[0] is None, -(r[0] or 0), r[1] or ""))
    want = []
    for i, r in enumerate(order):
        t, n = r[1] or "", order[(i + 1) % len(order)][1] or ""
        k = len(t) // 3
        e = t[: len(t) - k] + n[:k]
        f, g, h = (ctph.fingerprints([x])[0] for x in (t, e, n))
        want.append((r[0], len(t), hashlib.sha256(e.encode()).hexdigest(), f, g, round(ctph.likeness(f, g), 6), round(ctph.likeness(f, h), 6)))
    got = [tuple(r) for r in ctph.neighbours(edge(spark, rows)).collect()]
    assert sorted(got, key=repr) == sorted(want, key=repr)


PAGE = """<!DOCTYPE html><html><head><title>T</title><script>var t="</p>";</script><style>p{{}}</style></head><body><header><h2>Site name</h2></header>
<nav><ul><li><a href="/">Home {i}</a></li></ul></nav><div class="cookie-notice">We use cookies</div><div class=ad>Buy {i}!</div>
<main><article><h1>Head &amp; line {i}</h1><p><b>First  &lt;b&gt;<br>part {i}<p>Second &eacute;&nbsp;part {i}</p><ul><li>one {i}<li>two {i}</ul><div class="share">Share this</div>
<form><input><label>Mail</label></form><p class="tagline">Always the same words</p><table><tr><td>cell {i}<td>other {i}</table></article></main>
<section class="comments"><p>Reader {i} says hi</p></section><aside>Side {i}</aside><footer>&copy; {i}</footer></body></html>"""


def test_main_text(spark):
    rows = [(i, "https://a.example.com/x", PAGE.format(i=i)) for i in range(600)]
    rows += [(900, "https://b.example.com", None), (901, None, ""), (902, "https://lone.example.org/1", "<p>just <i>some</i> text<p>more"), (903, "bad url", "<div>unclosed <b>tags"), (None, "https://a.example.com/x", PAGE.format(i=7))]
    df = spark.createDataFrame([(*r, "clash") for r in rows], "page_id long, url string, html string, host string")
    got = {r.page_id: r for r in wrapper.main_text(df).collect()}
    assert len(got) == len(rows)
    for i in (0, 7, 599):
        assert got[i].text == f"Head & line {i}\nFirst <b> part {i}\nSecond é part {i}\none {i}\ntwo {i}\ncell {i}\nother {i}"
        assert got[i].n_chars == len(got[i].text)
    assert got[None].text == got[7].text
    assert got[900].text == got[901].text == "" and got[902].text == "just some text\nmore" and got[903].text == "unclosed tags"
    assert wrapper.main_text(df.limit(0)).collect() == []


NOTED = "<html><body><article><h1>Head {i}</h1><p>Text of page {i} in its own words</p><p class=tag>Always the same words</p><div class=note>Kept by us<p>Inner part {i}</p></div></article></body></html>"


@pytest.mark.parametrize("n", [8, 10, 40, 600])
def test_template_of_small_hosts(spark, n):
    rows = [(i, f"https://n.example.com/{i}", NOTED.format(i=i)) for i in range(n)]
    rows += [(1000 + i, f"https://copies.example.com/{i}", NOTED.format(i=0)) for i in range(n)] + [(2000, "https://lone.example.com", NOTED.format(i=0))]
    got = {r.page_id: r.text for r in wrapper.main_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    whole = "Head 0\nText of page 0 in its own words\nAlways the same words\nKept by us\nInner part 0"
    assert all(got[i] == f"Head {i}\nText of page {i} in its own words\nInner part {i}" for i in range(n))
    assert all(got[1000 + i] == whole for i in range(n)) and got[2000] == whole


SPLIT = {
    "title": "<body><article><h1>Head {i}</h1><div class=text><p>{long}</p></div></article></body>",
    "main": "<body><main><article><h1>Head {i}</h1><p>{long}</p></article><section class=notes><p>Note {i}</p></section></main></body>",
    "plain": "<body><div class=page><h1>Head {i}</h1><section class=long><p>{long}</p></section><section class=notes><p>Note {i}</p></section></div><div class=footer>Foot {i}</div></body>",
}


@pytest.mark.parametrize("kind", SPLIT)
def test_short_parts_beside_the_long_one(spark, kind):
    long = {i: f"word{i} " * 99 + "end" for i in range(12)}
    rows = [(i, f"https://s.example.com/{i}", SPLIT[kind].format(i=i, long=long[i])) for i in long]
    got = {r.page_id: r.text for r in wrapper.main_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert all(got[i] == f"Head {i}\n{long[i]}" + f"\nNote {i}" * (kind != "title") for i in long)
    body = SPLIT["main"].format(i=1, long="x")
    assert wrapper.extract(body, wrapper.path_of("body", "div.gone")) == "Head 1\nx\nNote 1"


def test_pages_without_semantic_tags(spark):
    page = "<html><body><div class=x1><div>Site</div></div><div class=x2><h1>Head {i}</h1><p>Text {i} {i}<p>more {i}</p><p class=x3>Same on all pages</p></div><div class=x4>Part of page {i} only</div><div class=footer>Foot {i}</div></body></html>"
    rows = [(i, f"https://d.example.com/{i}", page.format(i=i)) for i in range(40)]
    got = {r.page_id: r.text for r in wrapper.main_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert all(got[i] == f"Head {i}\nText {i} {i}\nmore {i}\nPart of page {i} only" for i in range(40))


def test_deep_pages(spark):
    n = 20_000
    deep = {
        1: "<div>" * n + "inmost" + "</div>" * n,
        2: "".join(f"<div>t{k % 7}" for k in range(n)),
        3: "<ul><li>" * n + "x",
        4: "<b>" * n + "bold",
        5: "<div><p>" * n + "</i>" * n + "end",
    }
    rows = [(k, f"https://deep.example.com/{k}", t) for k, t in deep.items()] + [(9, "https://deep.example.com/9", "<div>" * n + "other" + "</div>" * n)]
    got = {r.page_id: r.text for r in wrapper.main_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got[1] == "inmost" and got[9] == "other" and got[4] == "bold" and got[5] == "end" and got[3] == "x"
    assert got[2].split("\n") == [f"t{k % 7}" for k in range(n)]


def test_skeletons_survive_packing():
    for h in ("", "<p>a", "<div><p>a<ul><li>b</ul></div><div class=c>d</div><h1>e</h1>", "<div>" * 3000 + "x"):
        tree = wrapper.skeleton_of(h)
        shown = lambda t: [(p, q, d, s.label, s.digest, s.chars, off) for p, q, d, s, off in wrapper.slots(t)]
        assert shown(wrapper.unpacked(wrapper.packed(tree))) == shown(tree)


def test_alignment_counts_the_largest_match():
    tree = lambda h: wrapper.collapse([c for c in wrapper.parse(h).children if isinstance(c, wrapper.Node)])
    a, b = tree("<div><h1>x</h1><p>a</p><ul><li>q</ul></div>"), tree("<div><p>b</p><table><tr><td>z</table><ul><li>q</ul></div>")
    size, pairs = wrapper.align(a, b)
    assert size == 4 and sorted(x.label for x, _ in pairs) == ["div", "li", "p", "ul"]
    deep = "<p>x" * 5000
    assert wrapper.extract(deep).count("\n") == 4999


def test_generated_pages(spark, small):
    import html
    import re

    got = {r.page_id: r.text for r in queries.QUERIES["op10_main_text"](spark, small).collect()}
    for r in spark.read.parquet(f"{small}/pages.parquet").collect():
        body = re.search(r"<article>(.*?)</article>", r.html, re.S)[1]
        blocks = [" ".join(html.unescape(re.sub(r"</?b>|<br>", " ", x)).split()) for x in re.split(r"</?(?:p|h1)>", body)]
        assert got[r.page_id] == "\n".join(b for b in blocks if b)


def test_pipeline(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    ids = {r.doc_id for r in docs.select("doc_id").collect()}
    at = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        at = mixing.stored(stage(spark, at, small), f"test-{name}")
        assert at.columns == docs.columns
        left = [r.doc_id for r in at.select("doc_id").collect()]
        assert len(left) == len(set(left)) and set(left) <= ids
        ids = set(left)
    out = corpus_pipeline.run(spark, small).collect()
    assert {r.doc_id for r in out} == ids and all(len(r.token_ids) == r.n_tokens for r in out)


def test_pipeline_on_empty_tables_and_clashing_columns(spark, small, tmp_path):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    labels = spark.read.parquet(f"{small}/labels.parquet")
    for name, some in (("none", docs.limit(0)), ("clash", docs.withColumns({"node": F.lit("x"), "kept": F.lit(1), "topic": F.lit("t"), "token_ids": F.lit("y"), "__keep": F.lit(2)}))):
        some.write.parquet(f"{tmp_path}/{name}/documents.parquet")
        labels.write.parquet(f"{tmp_path}/{name}/labels.parquet")
    assert corpus_pipeline.run(spark, f"{tmp_path}/none").collect() == []
    plain, clash = (corpus_pipeline.run(spark, d).select("doc_id", "ids_sha256").collect() for d in (small, f"{tmp_path}/clash"))
    assert sorted(plain) == sorted(clash) and plain
