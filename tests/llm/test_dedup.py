"""Exact, line and near duplicates against brute force; nulls, empties, ties, repeats, clashing names."""

import hashlib
import random
import re
from collections import Counter, defaultdict

import numpy as np
import pytest

from bitplane.llm import bagminhash as bag
from bitplane.llm import common, exact_dedup, line_dedup, near_dedup

SCHEMA = "doc_id long, text string, keep_id string, comp string"


def lower(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")


def docs(spark, rows):
    return spark.createDataFrame([(i, t, "x", "y") for i, t in rows], SCHEMA)


EDGE = [(1, "Abc É"), (2, "aBC É"), (3, "abc é"), (4, None), (5, ""), (None, "abc É"), (7, "x" * 200_000), (8, "X" * 200_000), (9, "solo"), (9, "solo"), (None, "lone")]


@pytest.mark.parametrize("keep", ["largest", "smallest"])
def test_exact_groups(spark, keep):
    pick = max if keep == "largest" else min
    groups = defaultdict(list)
    for i, t in EDGE:
        groups[lower(t)].append(i)
    want = []
    for i, t in EDGE:
        ids = groups[lower(t)]
        known = [x for x in ids if x is not None]
        best = pick(known) if known else None
        want.append((i, best, len(ids), i == best, hashlib.sha256(lower(t).encode()).hexdigest()))
    got = [tuple(r) for r in exact_dedup.groups(docs(spark, EDGE), keep=keep).collect()]
    assert sorted(got, key=repr) == sorted(want, key=repr)


def test_exact_dedup_keeps_one_row_a_group(spark):
    kept = exact_dedup.dedup(docs(spark, EDGE))
    assert kept.columns == ["doc_id", "text", "keep_id", "comp"]
    assert sorted(((r.doc_id, lower(r.text)[:10]) for r in kept.collect()), key=repr) == sorted([(2, "abc É"), (3, "abc é"), (5, ""), (8, "xxxxxxxxxx"), (9, "solo"), (None, "lone")], key=repr)


def test_exact_many_copies_and_empty_table(spark):
    got = exact_dedup.groups(spark.range(5000).selectExpr("id as doc_id", "if(id % 3 = 0, 'hot', cast(id as string)) as text"))
    hot = got.where("group_size > 1")
    assert hot.count() == 1667 and hot.where("kept").first().keep_id == 4998
    assert exact_dedup.groups(docs(spark, [])).collect() == []
    assert exact_dedup.dedup(docs(spark, [])).collect() == []


def brute_lines(rows, min_chars=10, min_docs=2):
    key = lambda s: lower(s.strip(" \t\n\x0b\x0c\r"))
    holders = defaultdict(set)
    for i, t in rows:
        for s in (t or "").split("\n"):
            if len(key(s)) >= min_chars:
                holders[key(s)].add(i)
    out = []
    for i, t in rows:
        parts = (t or "").split("\n")
        def gone(s):
            h = holders.get(key(s), set())
            known = [x for x in h if x is not None]
            return len(h) >= min_docs and not (known and i == min(known))
        kept = [s for s in parts if not gone(s)]
        out.append((i, len(parts), len(parts) - len(kept), "\n".join(kept)))
    return sorted(out, key=repr)


@pytest.mark.parametrize("min_docs", [2, 3])
def test_lines(spark, min_docs):
    rnd = random.Random(3)
    pool = [" License line one\r", "license LINE one", "short", "Ünïcode line number", "ünïcode line number", "", "another long line here", "\tanother long line here", "\x1canother long line here"]
    rows = [(i, "\n".join(rnd.choices(pool + [f"own line number {i}"], k=rnd.randint(0, 9)))) for i in range(60)]
    rows += [(100, None), (101, ""), (None, "license line one\nfresh words in here"), (102, "\n\n"), (103, "another long line here\n" * 3000), (104, "tie line tie line\nx"), (104, "tie line tie line\ny")]
    got = sorted((tuple(r) for r in line_dedup.dedup_lines(docs(spark, rows), min_docs=min_docs).collect()), key=repr)
    assert got == brute_lines(rows, min_docs=min_docs)
    assert line_dedup.dedup_lines(docs(spark, [])).collect() == []


def brute_classes(rows, similarity=0.8):
    sets = []
    for _, t in rows:
        w = re.findall(r"\w+", (t or "").lower())
        sets.append(Counter(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else Counter())
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            k = sum((sets[a] & sets[b]).values())
            if k and k >= similarity * (sum(sets[a].values()) + sum(sets[b].values()) - k) - 1e-9:
                root[find(a)] = find(b)
    groups = defaultdict(list)
    for k in range(len(rows)):
        groups[find(k)].append(rows[k][0])
    out = []
    for k, (i, _) in enumerate(rows):
        ids = groups[find(k)]
        known = [x for x in ids if x is not None]
        best = (min(known) if known else None) if len(ids) > 1 else i
        out.append((i, best, len(ids), i == best))
    return sorted(out, key=repr)


def test_near_classes(spark):
    rnd = random.Random(5)
    words = [f"w{i}" for i in range(400)]
    rows, base = [], [rnd.choices(words, k=120) for _ in range(4)]
    for n in range(90):
        w = list(rnd.choice(base))
        for _ in range(rnd.choice([0, 0, 1, 2, 3, 5, 8])):
            w[rnd.randrange(len(w))] = rnd.choice(words)
        rows.append((n, " ".join(w)))
    rows += [(200, None), (201, ""), (202, "?!"), (203, "one two"), (204, "One, two!"), (205, "the same " * 400), (206, "the same " * 401), (None, "one two"), (207, "long " * 1000 + "tail"), (203, "one two")]
    got = sorted((tuple(r) for r in near_dedup.classes(docs(spark, rows)).collect()), key=repr)
    assert got == brute_classes(rows)
    assert near_dedup.classes(docs(spark, [])).collect() == []


def test_near_hot_group(spark, monkeypatch):
    """One group has most rows, copies and near copies, and its nodes are in blocks and pieces of a few."""
    monkeypatch.setattr(near_dedup, "BLOCK", 8)
    monkeypatch.setattr(near_dedup, "STAR", 4)
    rnd = random.Random(9)
    words, base = [f"w{i}" for i in range(500)], [f"b{i}" for i in range(100)]
    rows = []
    for n in range(150):
        w = list(base)
        for _ in range(rnd.choice([0, 1, 2, 3, 4, 6, 9, 14])):
            w[rnd.randrange(100)] = rnd.choice(words)
        rows.append((n if n % 3 else None, " ".join(w)))
    rows += [(1000 + n, " ".join(base)) for n in range(60)] + [(2000 + n, " ".join(rnd.choices(words, k=30))) for n in range(20)]
    got = sorted((tuple(r) for r in near_dedup.classes(docs(spark, rows)).collect()), key=repr)
    assert got == brute_classes(rows)


def test_near_spares_the_driver(spark, monkeypatch):
    """Stored tables meet without broadcasts, and the driver gives memory back between them."""
    plans, said = [], []
    put, back = common.Shelf.put, common.driver_gives_back
    monkeypatch.setattr(common.Shelf, "put", lambda self, df: plans.append(df._jdf.queryExecution().executedPlan().toString()) or put(self, df))
    monkeypatch.setattr(common, "driver_gives_back", lambda s: said.append(back(s)))
    words = [f"w{i}" for i in range(60)]
    rows = [(n, " ".join(words[n:] + [f"v{k}" for k in range(n)])) for n in range(12)] + [(100 + n, " ".join(words)) for n in range(4)]
    got = sorted((tuple(r) for r in near_dedup.classes(docs(spark, rows)).collect()), key=repr)
    assert got == brute_classes(rows)
    assert sum("SortMergeJoin" in p for p in plans) > 10
    assert sum("BroadcastExchange" in p for p in plans) <= 1  # at most where texts are fetched by their ids
    assert len(said) == len(plans) // near_dedup.REST > 1
    assert all(x.startswith("Trim native heap") for x in said)


def test_recall_at_the_threshold():
    """Share of pairs with a similarity of 0.8 to 0.82 that meet in a band."""
    rnd = random.Random(21)
    met = pairs = 0
    while pairs < 400:
        a = [f"r{rnd.randrange(10**9)}" for _ in range(200)]
        b = list(a)
        for _ in range(rnd.randint(3, 5)):
            b[rnd.randrange(200)] = "x"
        owner, hashes, weights, _ = bag.shingles([" ".join(a), " ".join(b)])
        x, y = set(hashes[owner == 0].tolist()), set(hashes[owner == 1].tolist())
        if 0.8 <= len(x & y) / len(x | y) <= 0.82:
            bands = bag.bands(bag.signatures(2, owner, hashes, weights, 6 * 32), 6)
            met, pairs = met + bool((bands[0] == bands[1]).any()), pairs + 1
    assert met / pairs >= 0.98


def test_near_dedup_keeps_columns(spark):
    text = " ".join(f"w{i}" for i in range(60))
    kept = near_dedup.dedup(docs(spark, [(1, text), (2, text + " more"), (3, "other words altogether in this one")]))
    assert kept.columns == ["doc_id", "text", "keep_id", "comp"] and sorted(r.doc_id for r in kept.collect()) == [1, 3]


def test_signatures_are_unbiased():
    rnd = random.Random(8)
    words = [f"v{i}" for i in range(300)]
    a = rnd.choices(words, k=60)
    texts = [" ".join(a * 3), " ".join(a * 3 + a[:30] * 2), " ".join(a * 2 + rnd.choices(words, k=40))]
    owner, hashes, weights, _ = bag.shingles(texts)
    sig = bag.signatures(3, owner, hashes, weights, 4096)
    multisets = [dict(zip(hashes[owner == i].tolist(), weights[owner == i].tolist())) for i in range(3)]
    for i, j in ((0, 1), (0, 2), (1, 2)):
        keys = set(multisets[i]) | set(multisets[j])
        lo = sum(min(multisets[i].get(k, 0), multisets[j].get(k, 0)) for k in keys)
        hi = sum(max(multisets[i].get(k, 0), multisets[j].get(k, 0)) for k in keys)
        assert abs(float(np.mean(sig[i] == sig[j])) - lo / hi) < 4 * np.sqrt(0.25 / 4096)
    again = bag.signatures(1, owner[owner == 1] * 0, hashes[owner == 1], weights[owner == 1], 4096)
    assert np.array_equal(again[0], sig[1])


def test_parity_bitmaps_never_overstate_a_difference():
    rnd = np.random.default_rng(5)
    sets = [np.unique(rnd.integers(0, 3000, size=k).astype(np.uint64)) for k in (0, 1, 40, 900, 2500) for _ in range(4)]
    mixed = [bag.mix(x) for x in sets]
    bound = np.r_[0, np.cumsum([len(x) for x in mixed])]
    maps = near_dedup.parities(np.concatenate(mixed), bound)
    for a, x in zip(maps, mixed):
        for b, y in zip(maps, mixed):
            differ = sum(bin(int(w) & (2**64 - 1)).count("1") for w in a ^ b)
            assert differ <= len(np.setxor1d(x, y)) and (differ - len(np.setxor1d(x, y))) % 2 == 0
