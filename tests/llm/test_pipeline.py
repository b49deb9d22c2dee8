"""Pipeline stages: columns, effects and edge tables."""

import random

import pytest
from pyspark.sql import functions as F

import corpus_pipeline as pipeline
from cubedensity.llm import simhash

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def tables(spark, folder, docs, benchmark, labels):
    docs.write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame(benchmark, "item_id bigint, text string").write.parquet(f"{folder}/benchmark.parquet")
    spark.createDataFrame(labels, "doc_id bigint, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    return str(folder)


def corpus(spark):
    rng = random.Random(12)
    word = lambda: "".join(rng.choice("abcdefghijklmnop") for _ in range(rng.randint(3, 8)))
    texts, kinds, item = [], [], " ".join(word() for _ in range(30))
    for i in range(120):
        words = [word() for _ in range(120)]
        if i % 6 == 0:
            words[5], words[70] = "vilename", "nastything"
        texts.append("\n".join(" ".join(words[k : k + 30]) for k in range(0, 120, 30)))
        kinds.append("toxic" if i % 6 == 0 else "clean")
    for i in (1, 2, 3):
        texts.append(texts[i])
        kinds.append("copy")
        near = texts[i + 6].split(" ")
        near[40] = word()
        texts.append(" ".join(near))
        kinds.append("near")
    for i in range(4):
        texts.append(" ".join(word() for _ in range(40)) + " " + item + ", " + " ".join(word() for _ in range(40)))
        kinds.append("leak")
    texts = [t + "\nall rights reserved by the makers of this site" if i % 3 else t for i, t in enumerate(texts)]
    rows = [(i, t, "en", "s", len(t)) for i, t in enumerate(texts)]
    labels = [(i, 1, int(k == "toxic")) for i, k in enumerate(kinds) if i < 120]
    return spark.createDataFrame(rows, DOCS), [(1, item), (2, None)], labels, kinds


def test_stages(spark, tmp_path):
    docs, benchmark, labels, kinds = corpus(spark)
    sf = tables(spark, tmp_path, docs, benchmark, labels)
    now, kept = spark.read.parquet(f"{sf}/documents.parquet"), []
    for _, stage in pipeline.STAGES:
        out = stage(spark, now, sf)
        if stage is not pipeline.STAGES[-1][1]:
            assert out.dtypes == docs.dtypes
        now = spark.createDataFrame(out.collect(), out.schema)
        kept.append({r.doc_id for r in now.collect()})
    of = lambda k: {i for i, x in enumerate(kinds) if x == k}
    assert kept[0] == set(range(len(kinds))) - of("toxic")
    assert kept[1] == kept[0]
    assert kept[2] == kept[1] - of("copy") - of("near")
    assert kept[3] == kept[2] - of("leak")
    assert kept[4] == kept[3]
    ran = pipeline.run(spark, sf)
    assert {r.doc_id for r in ran.collect()} == kept[4]


def test_lines_are_dropped_in_the_pipeline(spark, tmp_path):
    docs, benchmark, labels, _ = corpus(spark)
    out = pipeline.line_templates(spark, docs, str(tmp_path))
    assert out.filter(F.col("text").contains("all rights reserved")).isEmpty()
    assert out.filter("n_chars <> length(text)").isEmpty()


@pytest.mark.parametrize("rows", [[], [(None, None, None, None, None)] * 2 + [(1, "", "en", "s", 0), (1, "other", None, "s", 5), (1, "other", None, "s", 5)]])
def test_edge_tables(spark, tmp_path, rows):
    docs = spark.createDataFrame(rows, DOCS)
    sf = tables(spark, tmp_path, docs, [(1, "some item of words")], [(1, 1, 0), (None, None, None)])
    for _, stage in pipeline.STAGES:
        assert stage(spark, docs, sf).count() <= len(rows)
    assert pipeline.run(spark, sf).count() == (2 if rows else 0)  # the empty texts are one group


def test_keep_one_of_each_group_by_exact_similarity(spark):
    rng = random.Random(21)
    rows = []
    for _ in range(25):
        base = [f"w{rng.randrange(5000)}" for _ in range(rng.randint(60, 400))]
        for c in range(rng.randint(1, 4)):
            near = list(base)
            for _ in range(c * len(base) // 60):
                near[rng.randrange(len(near))] = f"w{rng.randrange(5000)}"
            rows.append((len(rows), " ".join(near)))
    rows.append(rows[0])
    df = spark.createDataFrame(rows, "doc_id bigint, text string").withColumn("node", F.lit(1)).withColumn("sketch", F.lit("x"))
    shingles = {i: {tuple(t.split()[k : k + 5]) for k in range(len(t.split()) - 4)} for i, t in rows}
    like = lambda a, b: len(shingles[a] & shingles[b]) / len(shingles[a] | shingles[b])
    out = simhash.keep_one(df)
    assert out.columns == df.columns
    got = [r.doc_id for r in out.collect()]
    assert len(got) == len(set(got))
    parent = {i: i for i in shingles}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for margin, check in ((0.75, "lost"), (0.87, "doubled")):
        parent = {i: i for i in shingles}
        for a in shingles:
            for b in shingles:
                if a < b and like(a, b) >= margin:
                    x, y = sorted((find(a), find(b)))
                    parent[y] = x
        groups = {find(i) for i in shingles}
        if check == "lost":  # every group of the wider relation keeps a row
            assert groups <= {find(i) for i in got}
        else:  # and hardly a group of the narrower one keeps two: candidates are found by chance
            assert sum(1 for g in groups if sum(find(i) == g for i in got) > 1) <= 0.1 * len(groups)


def test_resemblance_of_sketches():
    import numpy as np

    pack = lambda xs: np.array(sorted(xs), np.uint64).tobytes()
    assert simhash.resemblance(b"", b"") == 1 and simhash.resemblance(b"", pack([1])) == 0
    assert simhash.resemblance(pack([1, 2, 3]), pack([2, 3, 4])) == 0.5
    rng = np.random.default_rng(1)
    pool = rng.integers(0, 1 << 63, 3000, dtype=np.uint64)
    a, b = np.unique(pool[:2700]), np.unique(pool[300:])
    exact = len(np.intersect1d(a, b)) / len(np.union1d(a, b))
    assert abs(simhash.resemblance(a[:256].tobytes(), b[:256].tobytes()) - exact) < 0.08


def test_hot_group_of_edited_copies_loses_no_link(spark):
    rng = random.Random(33)
    base = [f"b{k}" for k in range(100)]
    rows = []
    for g in range(300):  # each copy is 0.81 of the original, and less of most other copies
        near = list(base)
        at = rng.randrange(5, 45)
        near[at], near[rng.randrange(at + 5, 95)] = f"e{g}x", f"e{g}y"
        rows.append((g, " ".join(near)))
    rows.append((1000, " ".join(base)))
    for g in range(40):  # unrelated texts that share a passage
        rows.append((2000 + g, " ".join(base[:20] + [f"u{g}x{k}" for k in range(100)])))
    sets = {i: {tuple(t.split()[k : k + 5]) for k in range(len(t.split()) - 4)} for i, t in rows}
    parent = {i: i for i in sets}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for a in sets:
        for b in sets:
            if a < b and len(sets[a] & sets[b]) / len(sets[a] | sets[b]) >= 0.8:
                x, y = sorted((find(a), find(b)))
                parent[y] = x
    got = simhash.wide_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()
    assert {r.doc_id: r.component_id for r in got} == {i: find(i) for i in sets}


def exact_pairs(texts, least=0.8):
    """All pairs of texts whose sets of five-word shingles have a similarity of ``least`` or more, by whole sets."""
    import math
    from collections import Counter, defaultdict

    sets = []
    for t in texts:
        words = (t or "").encode().lower().split()
        sets.append({b" ".join(words[k : k + 5]) for k in range(max(1, len(words) - 4))} if words else set())
    count = Counter(s for held in sets for s in held)
    found, index = set(), defaultdict(list)
    for i, held in enumerate(sets):
        rare = sorted(held, key=lambda s: (count[s], s))[: len(held) - math.ceil(least * len(held)) + 1]
        near = {j for s in rare for j in index[s] if least <= len(sets[j]) / len(held) <= 1 / least}
        found |= {(j, i) for j in near if len(held & sets[j]) >= least * len(held | sets[j])}
        for s in rare:
            index[s].append(i)
    return found


@pytest.mark.skipif(not __import__("os").path.isdir("/root/testdata/sf0.01"), reason="needs the given tables")
def test_recall_over_all_pairs_of_the_given_table(spark):
    rows = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text").collect()
    pairs = exact_pairs([r.text for r in rows])
    groups = simhash.wide_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()
    of = {r.doc_id: r.group for r in groups}
    met = sum(of[rows[i].doc_id] == of[rows[j].doc_id] for i, j in pairs)
    print(f"{met} of {len(pairs)} pairs")
    assert len(pairs) > 50 and met >= 0.9 * len(pairs)


def test_texts_that_share_a_passage_both_stay(spark):
    rng = random.Random(4)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(6))
    passage = " ".join(word() for _ in range(30)) + " "
    rows = [(i, passage * 12 + " ".join(word() for _ in range(60))) for i in range(2)]
    assert simhash.keep_one(spark.createDataFrame(rows, "doc_id bigint, text string")).count() == 2


def test_fingerprints_link_texts_by_themselves(spark, monkeypatch):
    rng = random.Random(5)
    base = [[f"w{rng.randrange(5000)}" for _ in range(120)] for _ in range(4)]
    rows = [(10 * i + k, " ".join(w) if k == 0 else " ".join(w).upper() if k == 1 else "  ".join(w)) for i, w in enumerate(base) for k in range(3)]
    # one passage over and over: one fingerprint for both, and little else in common
    rows += [(90 + k, "a b c d e f g h i j " * 60 + " ".join(f"x{k}_{i}" for i in range(300))) for k in range(2)]
    # no shingle hash becomes a key, so all links are those of the fingerprints
    monkeypatch.setattr(simhash, "prefixes", lambda nodes, least: nodes.limit(0).select("node", F.lit(0).alias("size"), F.lit(0).cast("bigint").alias("key")))
    got = simhash.keep_one(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()
    assert sorted(r.doc_id for r in got) == [0, 10, 20, 30, 90, 91]
