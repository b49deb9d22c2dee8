"""SimHash groups and benchmark matches against brute force."""

import hashlib
import random
import re

import pytest
import xxhash
from pyspark.sql import functions as F

from cubedensity.llm import components, decontam, simhash

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def corpus(seed=3):
    rng = random.Random(seed)
    words = ["Ab", "cé", "the", "of", "x1", "Über", "no", "yes.", "q"]
    texts = [None, "", "   ", "one", "One", "two words", "a\tb\x0bc\r\nd", "na me x y"]
    for _ in range(30):
        base = [rng.choice(words) for _ in range(rng.randint(1, 400))]
        texts.append(" ".join(base))
        if rng.random() < 0.6:
            for _ in range(3):
                near = list(base)
                near[rng.randrange(len(near))] = rng.choice(words)
                texts.append(" ".join(near))
    rows = [(i * 3 % 251, t) for i, t in enumerate(texts)]
    return rows + [rows[-1], (None, rows[-1][1]), (None, "zzz unique null id"), (7, "extra with seven")]


def fingerprint(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    words = re.findall(r"[^\x20\x09-\x0D]+", low)
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    hs = [xxhash.xxh64_intdigest(s.encode(), seed=42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def brute_groups(rows):
    fps = [fingerprint(t) for _, t in rows]
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 2:
                root[find(i)] = find(j)
    groups = {}
    for i in range(len(rows)):
        groups.setdefault(find(i), []).append(rows[i][0])
    least = {g: min((x for x in ids if x is not None), default=None) for g, ids in groups.items()}
    return sorted(((rows[i][0], f"{fps[i]:016x}", least[find(i)]) for i in range(len(rows))), key=str)


def check(spark, rows):
    got = simhash.near_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()
    assert sorted(map(tuple, got), key=str) == brute_groups(rows)


def test_groups(spark):
    check(spark, corpus())


def test_groups_with_hot_keys(spark, monkeypatch):
    monkeypatch.setattr(simhash, "HOT_KEY", 2)
    check(spark, corpus(5))


def test_near_edges_of_dense_words(spark):
    rng = random.Random(1)
    base = rng.getrandbits(64)
    words = sorted({base ^ sum(1 << b for b in rng.sample(range(64), rng.randint(0, 4))) for _ in range(300)})
    signed = [(w - (1 << 64) if w >> 63 else w,) for w in words]
    df = spark.createDataFrame(signed, "fp bigint")
    for hot in (2, 64, 1000):
        simhash.HOT_KEY = hot
        try:
            found = {tuple(r) for r in components.components(simhash.near_edges(df)).collect()}
        finally:
            simhash.HOT_KEY = 64
        root = dict(found)
        parent = {s[0]: s[0] for s in signed}

        def find(x):
            while parent[x] != x:
                x = parent[x]
            return x

        for i, (a,) in enumerate(signed):
            for (b,) in signed[:i]:
                if ((a ^ b) & (1 << 64) - 1).bit_count() <= 2:
                    x, y = sorted((find(a), find(b)))
                    parent[y] = x
        want = {x: find(x) for x in parent}
        assert {x: root.get(x, x) for x in parent} == want


@pytest.mark.parametrize("few", [0, components.FEW])
def test_components_of_few_and_many_edges(spark, monkeypatch, few):
    rng, cuts = random.Random(8), []
    edges = [(rng.randrange(-300, 300), rng.randrange(-300, 300)) for _ in range(250)] + [(7, 7)]
    held, parent = components.durable, {x: x for e in edges for x in e if e[0] != e[1]}
    monkeypatch.setattr(components, "durable", lambda df: cuts.append(1) or held(df))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges[:-1]:
        if a != b:
            a, b = sorted((find(a), find(b)))
            parent[b] = a
    df = spark.createDataFrame(edges, "u bigint, v bigint")
    assert sorted(map(tuple, components.components(df, few).collect())) == sorted((x, find(x)) for x in parent)
    assert (len(cuts) == 1) == (few > 0)  # no rounds of small tables
    assert components.components(df.limit(0), few).count() == 0


def test_components_path(spark):
    edges = spark.range(60).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"))
    got = {r.node: r.root for r in components.components(edges).collect()}
    assert got == dict.fromkeys(range(61), 0)


def test_empty_tables(spark):
    empty = spark.createDataFrame([], DOCS)
    bench = spark.createDataFrame([], "item_id bigint, text string")
    assert simhash.near_duplicates(empty).count() == 0
    assert simhash.wide_duplicates(empty).count() == 0
    assert decontam.contamination(empty, bench).count() == 0
    some = spark.createDataFrame([(1, "a b")], "doc_id bigint, text string")
    assert decontam.contamination(some, bench).first().contaminated is False


def test_wide_groups(spark):
    rng = random.Random(9)
    rows, truth = [], {}
    for g in range(12):
        base = [f"w{rng.randrange(3000)}" for _ in range(300)]
        for c in range(6):
            near = list(base)
            for _ in range(c and 3):
                near[rng.randrange(len(near))] = f"w{rng.randrange(3000)}"
            truth[len(rows)] = g
            rows.append((len(rows), " ".join(near)))
    got = {r.doc_id: r.component_id for r in simhash.wide_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    assert got == {i: min(j for j in truth if truth[j] == truth[i]) for i in truth}


WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def words(text):
    return WORD.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))


def brute_contamination(docs, items, window=10):
    out = []
    for doc_id, text in docs:
        w = words(text)
        hit, who = set(), set()
        for item_id, item in items:
            v = words(item)
            if not v:
                continue
            size = min(window, len(v))
            for a in range(len(v) - size + 1):
                for p in range(len(w) - size + 1):
                    if w[p : p + size] == v[a : a + size]:
                        hit |= set(range(p, p + size))
                        who.add(str(item_id))
        out.append((doc_id, len(w), len(hit), len(who), hashlib.sha256(",".join(sorted(who)).encode()).hexdigest(), bool(hit)))
    return sorted(out, key=str)


def passages(seed=4):
    rng = random.Random(seed)
    vocabulary = ["a", "b", "cé", "d2", "E"]
    items = [(i * 7, " ".join(rng.choice(vocabulary) for _ in range(rng.randint(1, 25)))) for i in range(12)]
    items += [(500, None), (501, "..."), (502, "Lone"), items[0], (503, items[1][1])]
    docs = [(0, None), (1, ""), (2, "- - -"), (None, "x " + items[3][1])]
    for i in range(40):
        parts = [" ".join(rng.choice([*vocabulary, "zz"]) for _ in range(rng.randint(0, 30)))]
        if i % 2:
            v = words(rng.choice(items[:12])[1])
            k = rng.randrange(len(v))
            parts.append(", ".join(v[k:]).upper())
            parts.append(" ".join(rng.choice(vocabulary) for _ in range(5)))
        docs.append((10 + i, " ".join(parts)))
    return docs + docs[-2:] + [(99, "a lone-wolf")], items


def test_contamination(spark, monkeypatch):
    docs, items = passages()
    d = spark.createDataFrame(docs, "doc_id bigint, text string").withColumn("matches", F.lit(1))
    b = spark.createDataFrame(items, "item_id bigint, text string")
    want = brute_contamination(docs, items)
    assert sorted(map(tuple, decontam.contamination(d, b).collect()), key=str) == want
    monkeypatch.setattr(decontam, "SHARD_WORDS", 50)
    assert sorted(map(tuple, decontam.contamination(d, b).collect()), key=str) == want
    clean = decontam.decontaminate(d, b)
    assert clean.columns == d.columns
    assert clean.count() == sum(not w[-1] for w in want)


def test_benchmark_in_blocks(spark):
    docs, items = passages(8)
    d = spark.createDataFrame(docs, "doc_id bigint, text string")
    b = spark.createDataFrame(items, "item_id bigint, text string")
    found = decontam.longest_matches(d, b, block_chars=60)
    got = found.select("doc_id", "n_words", decontam.hit_words(F.col("matches")).alias("n")).collect()
    assert sorted(map(tuple, got), key=str) == sorted([w[:3] for w in brute_contamination(docs, items)], key=str)


def test_longest_match_and_place(spark):
    item = " ".join(f"w{i}" for i in range(30))
    text = "x y " + " ".join(f"W{i}" for i in range(5, 25)) + " z"
    row = decontam.longest_matches(
        spark.createDataFrame([(1, text)], "doc_id bigint, text string"), spark.createDataFrame([(4, item)], "item_id bigint, text string")
    ).first()
    assert [tuple(m) for m in row.matches] == [("4", 2, 5, 20)]
