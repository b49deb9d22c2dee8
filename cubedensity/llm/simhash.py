"""SimHash fingerprints and near-duplicate groups by pigeonhole blocks.

A fingerprint is cut into blocks of bits. If two fingerprints differ in at most ``k`` bits, at most ``k`` blocks
differ, so the pair agrees on some set of ``blocks - k`` blocks: each such set is a key, and pairs that share a key
are verified by their Hamming distance. Only distinct fingerprints are compared, so exact copies cost nothing.

A key that many fingerprints share is not compared pair by pair. For ``k = 2`` its members go through single-bit
neighbours instead: two words within two bits have a common neighbour within one bit of both, and a word has at
most 65 of those, so the work stays linear and no link is lost.

Near duplicates by shingle similarity (``wide_duplicates``) begin with the same fingerprints, blocks and Hamming distance,
whose links are verified by similarity before texts are merged. That alone is not the whole job: five-word sets that share
four fifths differ in some 20 of 128 fingerprint bits, and blocks that such pairs share for certain are too short to tell
texts apart. What the fingerprints leave apart goes through blocks of shingle hashes: the rarest fifth of the least hashes
of a text, of which similar texts share one for certain, and every pair is verified.

Inputs: null texts count as empty; an empty text has fingerprint zero and links as any other; texts of any length are read
whole; repeated rows give repeated results; a null id takes part and never becomes the component's name unless all ids in
it are null; of equal ids any serves, and the least id names a component; an empty table gives none; extra columns, of
whatever name, are not returned (``keep_one`` returns all columns as they are).
"""

from __future__ import annotations

import math
from itertools import combinations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubedensity.llm.common import content_key, durable, released, tidy
from cubedensity.llm.components import components

HOT_KEY = 64
CHUNK = 1 << 16
#: least hashes of a text's distinct shingles that are kept to estimate similarity; exact for texts of no more shingles
SKETCH = 256
#: one in so many nodes has its hashes counted to find common ones; common hashes that are told apart, at most
SAMPLED = 4
COMMON = 200_000


def fingerprint_bytes(text: bytes, shingle: int) -> bytes:
    """Majority bits over the hashes of all shingles of a text, repeats included, most significant bit first."""
    words = text.lower().split()  # bytes: A-Z and ASCII white space only
    if not words:
        return bytes(8)
    line = b" ".join(words)
    n = max(1, len(words) - shingle + 1)
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(sizes + 1) - 1
    starts = (ends - sizes)[:n].tolist()
    ends = (ends[shingle - 1 :] if len(words) >= shingle else ends[-1:]).tolist()
    seen = np.zeros(64, np.int64)
    for at in range(0, n, CHUNK):
        hashed = b"".join([xxhash.xxh64_digest(line[s:e], 42) for s, e in zip(starts[at : at + CHUNK], ends[at : at + CHUNK])])
        seen += np.unpackbits(np.frombuffer(hashed, np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int32)
    return np.packbits(2 * seen > n).tobytes()


def fingerprints(docs: DataFrame, shingle: int = 3) -> DataFrame:
    """``(doc_id, text) -> (doc_id, fp)``: 64 bits as a long."""

    def run(batches):
        for batch in batches:
            made = [fingerprint_bytes(t or b"", shingle) for t in pc.cast(batch.column("text"), pa.binary()).to_pylist()]
            longs = np.frombuffer(b"".join(made), ">i8").astype(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(longs, pa.int64())], names=["doc_id", "fp"])

    kind = dict(docs.dtypes)["doc_id"]
    return docs.select("doc_id", "text").mapInArrow(released(run), f"doc_id {kind}, fp bigint")


def block_masks(bits: int, blocks: int, keep: int) -> list[int]:
    """Masks (as signed longs) of all sets of ``keep`` blocks out of ``blocks`` over the low ``bits`` bits."""
    cut = [bits * i // blocks for i in range(blocks + 1)]
    each = [((1 << (b - a)) - 1) << a for a, b in zip(cut, cut[1:])]
    sums = [sum(s) for s in combinations(each, keep)]
    return [m - (1 << 64) if m >= 1 << 63 else m for m in sums]


def _keyed(nodes: DataFrame, masks: list[tuple[str, int]], carry: list[str]) -> DataFrame:
    keys = F.array(*(F.struct(F.lit(i).alias("c"), F.col(col).bitwiseAND(F.lit(m)).alias("k")) for i, (col, m) in enumerate(masks)))
    return nodes.select(*carry, F.explode(keys).alias("_b")).select(*carry, "_b.c", "_b.k")


def _shared(keyed: DataFrame) -> DataFrame:
    """Members of keys that at least two distinct fingerprints have, with the size of the key."""
    sizes = durable(keyed.groupBy("c", "k").agg(F.count("*").alias("n"), F.min("fp").alias("rep")).filter("n > 1"))
    return durable(keyed.join(sizes, ["c", "k"]))


def _pairs(members: DataFrame, cols: list[str], close) -> DataFrame:
    """Verified pairs inside keys of at most HOT_KEY members."""
    light = members.filter(F.col("n") <= HOT_KEY)
    a = light.select("c", "k", *(F.col(x).alias(f"a_{x}") for x in cols))
    b = light.select("c", "k", *(F.col(x).alias(f"b_{x}") for x in cols))
    return a.join(b, ["c", "k"]).filter(close)


def hamming(a: str, b: str):
    return F.bit_count(F.col(a).bitwiseXOR(F.col(b)))


def near_edges(nodes: DataFrame, k: int = 2) -> DataFrame:
    """Links ``(u, v)`` among distinct 64-bit fingerprints ``fp`` whose components are those of all pairs within 2 bits."""
    if k != 2:
        raise ValueError("linear handling of hot keys is worked out for two bits")
    members = _shared(_keyed(nodes.select("fp"), [("fp", m) for m in block_masks(64, 5, 3)], ["fp"]))
    light = _pairs(members, ["fp"], (F.col("a_fp") < F.col("b_fp")) & (hamming("a_fp", "b_fp") <= k)).select(
        F.col("a_fp").alias("u"), F.col("b_fp").alias("v")
    )
    hot = members.filter(F.col("n") > HOT_KEY).select("fp").distinct()
    flips = F.array(F.lit(0).cast("long"), *(F.shiftleft(F.lit(1).cast("long"), i) for i in range(64)))
    middle = hot.select("fp", F.explode(flips).alias("x")).select("fp", F.col("fp").bitwiseXOR(F.col("x")).alias("mid"))
    star = middle.groupBy("mid").agg(F.collect_set("fp").alias("near")).filter(F.size("near") > 1)  # 65 at most
    hot_edges = star.select(F.array_min("near").alias("u"), F.explode("near").alias("v"))
    return light.union(hot_edges).filter("u <> v")


def near_duplicates(docs: DataFrame, shingle: int = 3, k: int = 2) -> DataFrame:
    """``(doc_id, fingerprint, component_id)`` for every row of ``docs(doc_id, text)``."""
    fps = durable(fingerprints(docs, shingle))
    nodes = durable(fps.groupBy("fp").agg(F.min("doc_id").alias("least")))
    linked = components(near_edges(nodes, k))
    rooted = durable(
        nodes.join(linked, nodes["fp"] == linked["node"], "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    )
    named = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    naming = durable(rooted.select("fp", "root").join(named, "root").select(F.col("fp").alias("nfp"), "component_id"))
    return fps.join(naming, F.col("fp") == F.col("nfp")).select(
        "doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id"
    )


def resemblance(a: bytes, b: bytes, keep: int = SKETCH, kind=np.uint64) -> float:
    """Similarity of two sets of shingles from their least hashes; exact if both are held whole."""
    if not a or not b:
        return float(a == b)
    p, q = np.frombuffer(a, kind), np.frombuffer(b, kind)
    union = np.union1d(p, q)
    if max(len(p), len(q)) == keep:
        union = union[:keep]
    return np.isin(union, p, assume_unique=True).__and__(np.isin(union, q, assume_unique=True)).sum() / len(union)


def sketch_bytes(text: bytes, shingle: int, keep: int = SKETCH) -> bytes:
    """The least distinct hashes of a text's shingles, in order, as eight bytes each."""
    words = text.lower().split()  # bytes: A-Z and ASCII white space only
    least = np.zeros(0, np.uint64)
    n = max(1, len(words) - shingle + 1) if words else 0
    for at in range(0, n, CHUNK):
        hashed = [xxhash.xxh3_64_intdigest(b" ".join(words[i : i + shingle]), 42) for i in range(at, min(n, at + CHUNK))]
        least = np.unique(np.concatenate([least, np.array(hashed, np.uint64)]))[:keep]
    return least.tobytes()


def sketches(docs: DataFrame, shingle: int = 5, keep: int = SKETCH, words: int = 3) -> DataFrame:
    """``(doc_id, node, text) -> (doc_id, node, sketch, fp)``: least hashes, and the fingerprint of shingles of ``words`` words."""

    def run(batches):
        for batch in batches:
            texts = [t or b"" for t in pc.cast(batch.column("text"), pa.binary()).to_pylist()]
            made = pa.array([sketch_bytes(t, shingle, keep) for t in texts], pa.binary())
            longs = np.frombuffer(b"".join(fingerprint_bytes(t, words) for t in texts), ">i8").astype(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("node"), made, pa.array(longs, pa.int64())], names=["doc_id", "node", "sketch", "fp"])

    kind = dict(docs.dtypes)["doc_id"]
    return docs.select("doc_id", "node", "text").mapInArrow(released(run), f"doc_id {kind}, node bigint, sketch binary, fp bigint")


def common_hashes(nodes: DataFrame) -> np.ndarray:
    """Hashes that several of a ``SAMPLED``th of the nodes hold, rarest first, COMMON at most.

    They only set the order in which hashes become keys: any order finds every pair, one with the rare hashes first
    makes fewer candidates.
    """

    def run(batches):
        for batch in batches:
            held = b"".join(batch.column("sketch").to_pylist())
            yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(held, np.uint64).view(np.int64))], names=["h"])

    each = nodes.filter(F.pmod(F.xxhash64("node"), F.lit(SAMPLED)) == 0).select("sketch").mapInArrow(released(run), "h bigint")
    top = each.groupBy("h").agg(F.count("*").alias("n")).filter("n > 1").orderBy(F.desc("n"), "h").limit(COMMON)
    return np.array([r.h for r in top.collect()][::-1], np.int64).view(np.uint64)


def prefix_keys(sketch: bytes, least: float, common: np.ndarray, place: np.ndarray) -> np.ndarray:
    """The hashes of a sketch of which a sketch of similarity ``least`` or more shares one at least.

    Similar sketches share ``least`` of the hashes of each. So if all hashes stand in one order, the first of the shared
    ones has that many behind it in both, and is among the rest in front. The order: hashes that are not common by value,
    then the common ones, rarest first; ``common`` is sorted and ``place`` gives the rank of each.
    """
    h = np.frombuffer(sketch, np.uint64)
    n = len(h) - math.ceil(least * len(h) - 1e-9) + 1 if len(h) else 0
    if len(common):
        at = np.minimum(np.searchsorted(common, h), len(common) - 1)
        rank = np.where(common[at] == h, place[at], -1)
        h = h[np.argsort(rank, kind="stable")]
    return h[:n]


def prefixes(nodes: DataFrame, least: float) -> DataFrame:
    """``(node, size, key)``: the keys of every node, and the size of its sketch."""
    found = common_hashes(nodes)
    place = np.argsort(found)
    common = found[place]

    def run(batches):
        for batch in batches:
            held = batch.column("sketch").to_pylist()
            keys = [prefix_keys(s, least, common, place) for s in held]
            many = [len(k) for k in keys]
            node = np.repeat(batch.column("node").to_numpy(), many)
            size = np.repeat(np.array([len(s) // 8 for s in held], np.int32), many)
            key = np.concatenate([np.zeros(0, np.uint64), *keys]).view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(node), pa.array(size), pa.array(key)], names=["node", "size", "key"])

    return nodes.select("node", "sketch").mapInArrow(released(run), "node bigint, size int, key bigint")


def similar(edges: DataFrame, nodes: DataFrame, least: float, keep: int = SKETCH) -> DataFrame:
    """Links whose texts have a similarity of ``least`` or more, by the sketches of ``nodes(node, sketch)``.

    The upper halves of the hashes tell them apart as well and keep their order; only those travel.
    """

    def halves(batches):
        for batch in batches:
            made = [(np.frombuffer(s, np.uint64) >> np.uint64(32)).astype(np.uint32).tobytes() for s in batch.column("sketch").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("node"), pa.array(made, pa.binary())], names=["node", "sketch"])

    def run(batches):
        for batch in batches:
            both = zip(batch.column("a").to_pylist(), batch.column("b").to_pylist())
            near = [resemblance(a, b, keep, np.uint32) >= least for a, b in both]
            yield batch.select(["u", "v"]).filter(pa.array(near, pa.bool_()))

    ends = edges.select(F.col("u").alias("node")).union(edges.select("v")).distinct()
    held = nodes.select("node", "sketch").join(ends, "node", "left_semi").mapInArrow(released(halves), "node bigint, sketch binary")
    held = durable(held)
    both = edges.join(held.select(F.col("node").alias("u"), F.col("sketch").alias("a")), "u")
    both = both.join(held.select(F.col("node").alias("v"), F.col("sketch").alias("b")), "v")
    return both.select("u", "v", "a", "b").mapInArrow(released(run), "u bigint, v bigint")


def _rooted(members: DataFrame, near: DataFrame) -> DataFrame:
    """Members of keys whose nodes the links do not connect yet, with the component that each is in."""
    roots = components(near).select(F.col("node").alias("_n"), "root")
    rooted = members.join(roots, F.col("node") == F.col("_n"), "left").select("key", "node", "size", "n", F.coalesce("root", "node").alias("root"))
    rooted = durable(rooted)
    mixed = rooted.groupBy("key").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).filter("lo < hi").select("key")
    return durable(rooted.join(mixed, "key", "left_semi"))


def fingerprint_pairs(nodes: DataFrame) -> DataFrame:
    """Pairs ``(u, v)`` of ``nodes(node, fp)`` that connect all whose fingerprints link, to be verified.

    A node is paired with the least one of its fingerprint, and those of two fingerprints that link with each other.
    """
    heads = durable(nodes.groupBy("fp").agg(F.min("node").alias("head")))
    same = nodes.select("node", "fp").join(heads, "fp").filter("node <> head").select(F.col("head").alias("u"), F.col("node").alias("v"))
    named = lambda end, to: heads.select(F.col("fp").alias(end), F.col("head").alias(to))
    across = near_edges(heads.select("fp")).join(named("u", "a"), "u").join(named("v", "b"), "v")
    return same.union(across.select(F.col("a").alias("u"), F.col("b").alias("v")))


def similar_links(nodes: DataFrame, least: float, keep: int = SKETCH) -> DataFrame:
    """Links ``(u, v)`` whose components are those of all pairs of ``nodes(node, sketch, fp)`` with a similarity of ``least`` or more.

    First come the pairs that the fingerprints link. Every pair of that similarity shares a key as well: each node is tried
    against one other, of those that lead its keys the one that shares most keys with others, as an original does with its
    copies. In keys that this leaves in several components, all nodes
    are tried against the key's leader, and then all pairs that are not connected by now; pairs inside one component can
    add nothing. So a group of near copies costs links in proportion to its size.
    """
    keyed = durable(prefixes(nodes, least))
    sizes = durable(keyed.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1"))
    members = durable(keyed.join(sizes, "key"))
    weight = durable(members.groupBy("node").agg(F.sum("n").alias("w")))
    del keyed, sizes
    tidy(nodes.sparkSession)
    ordered = lambda rows: rows.select(F.least("node", "v").alias("u"), F.greatest("node", "v").alias("v"))

    def leaders(rows):
        first = rows.select("key", "node").join(weight, "node").groupBy("key").agg(F.max(F.struct("w", "node")).alias("lead"))
        return rows.join(first, "key").filter("node <> lead.node")

    one = leaders(members).groupBy("node").agg(F.max("lead")["node"].alias("v"))
    linked = fingerprint_pairs(nodes).select(F.col("u").alias("node"), "v")
    tried = durable(ordered(linked.union(one)).distinct())
    del linked, one
    tidy(nodes.sparkSession)
    near = durable(similar(tried, nodes, least, keep))
    del tried
    tidy(nodes.sparkSession)
    open_ = _rooted(members, near)
    del members
    tidy(nodes.sparkSession)
    if open_.isEmpty():
        return near
    star = leaders(open_).select("node", F.col("lead.node").alias("v"), "root").join(open_.select(F.col("node").alias("v"), F.col("root").alias("r")).distinct(), "v").filter("root <> r")
    near = durable(near.union(similar(durable(ordered(star).distinct()), nodes, least, keep)))
    open_ = _rooted(open_.select("key", "node", "size", "n"), near)
    tidy(nodes.sparkSession)
    a = open_.select("key", *(F.col(x).alias(f"a_{x}") for x in ("node", "size", "root")))
    b = open_.select("key", *(F.col(x).alias(f"b_{x}") for x in ("node", "size", "root")))
    # similar sketches have like sizes
    sized = F.least("a_size", "b_size") >= F.lit(least - 1e-9) * F.greatest("a_size", "b_size")
    pairs = a.join(b, "key").filter((F.col("a_root") < F.col("b_root")) & sized)
    rest = durable(pairs.select(F.least("a_node", "b_node").alias("u"), F.greatest("a_node", "b_node").alias("v")).distinct())
    return near.union(similar(rest, nodes, least, keep))


def wide_duplicates(docs: DataFrame, shingle: int = 5, least: float = 0.8, keep: int = SKETCH) -> DataFrame:
    """Near duplicates of five-word shingle similarity ``least`` or more: ``(doc_id, component_id, group)``.

    Links of the fingerprints are verified, and the pairs that they leave apart are sought among shingle hashes. Similarity is that of the sketches, which is exact for texts of fewer than ``keep`` shingles; no pair is left out.
    Equal texts are one node; texts without words form one group.
    """
    text = F.coalesce("text", F.lit(""))
    keyed = docs.select("doc_id", F.when(text.rlike("[^ \\t-\\r]"), F.xxhash64(text)).otherwise(0).alias("node"), "text")
    nodes = durable(sketches(keyed, shingle, keep).groupBy("node").agg(F.min("doc_id").alias("least"), F.min("sketch").alias("sketch"), F.min("fp").alias("fp")))
    linked = components(similar_links(nodes, least, keep))
    rooted = durable(
        nodes.join(linked.withColumnRenamed("node", "n2"), F.col("node") == F.col("n2"), "left").select(
            "node", "least", F.coalesce("root", "node").alias("root")
        )
    )
    named = durable(rooted.groupBy("root").agg(F.min("least").alias("component_id")))
    naming = durable(rooted.join(named, "root").select(F.col("node").alias("nn"), "component_id", F.col("root").alias("group")))
    return keyed.select("doc_id", "node").join(naming, F.col("node") == F.col("nn")).select("doc_id", "component_id", "group")


def keep_one(docs: DataFrame) -> DataFrame:
    """``docs`` with one row of each group of near duplicates: the least by id, then by hash of the text.

    Repeated rows are one group; the columns stay as they are. Ids need not be unique or set; of rows equal in id and text
    the one stays whose columns, written as JSON, come first.
    """
    columns = docs.columns
    keyed = docs.select(F.struct(*columns).alias("row"), *content_key(), F.col("text"))
    # groups are found for (id, text hash) pairs, so the join below tells rows with one id apart
    marked = wide_duplicates(keyed.select(F.struct(F.col("_kid").isNull().alias("z"), "_kid", "_kh").alias("doc_id"), "text"))
    counted = marked.groupBy("group", "doc_id").agg(F.count("*").alias("n"))
    least = counted.groupBy("group").agg(F.min(F.struct("doc_id", "n")).alias("k"))
    first = durable(least.select(F.col("k.doc_id._kid").alias("_fid"), F.col("k.doc_id._kh").alias("_fh"), F.col("k.n").alias("_n")))
    kept = keyed.select("row", "_kid", "_kh").join(first, F.col("_kid").eqNullSafe(F.col("_fid")) & (F.col("_kh") == F.col("_fh")))
    # only rows that are equal in id and text to another need a second look
    repeated = kept.filter("_n > 1").groupBy("_kid", "_kh").agg(F.min_by("row", F.to_json("row")).alias("row"))
    return kept.filter("_n = 1").select("row.*").union(repeated.select("row.*"))
