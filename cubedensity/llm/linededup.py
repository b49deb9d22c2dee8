"""Line deduplication with a log-template tree of fixed depth.

A line is cut into lower-cased tokens, with fields that carry digits, addresses or links generalised to a wildcard. Its
leaf in the tree is its token count and its first ``LEAD`` tokens. A leaf holds any number of templates: a line joins the
template of a leader that it agrees with in ``ALIKE`` of its tokens or more, or leads a new one; templates with a line in
common are one. Lines that agree share one of a few runs of tokens for certain (they differ in fewer places than a line
has runs), so a line is tried against the leaders of its runs, and where many lines share a run they are dealt out by
hash first and their leaders meet in a second round. Tokens are compared by 32-bit prints.

A template recurs if it stands in ``LEAST_TEXTS`` documents or more (``SHORT_TEXTS`` if its lines have fewer than ``SHORT``
tokens); all its lines are dropped from all documents. Copies are documents like any other.

With ``copies`` above zero, only texts count that are unlike each other: a text whose similarity to a counted one, over
runs of five tokens, is ``copies`` or more does not count again. So the lines that only copies of one text share, near or
exact, are left to the removal of near duplicates, which would find nothing to keep otherwise. Similarity is estimated from
the ``SKETCH`` least hashes of a text, and exact for texts of fewer runs.

Inputs: null texts stay null and have no lines; empty lines and short lines of variable fields only are kept; a text whose
lines are all dropped stays as an empty text; repeated rows are documents each and are treated alike; of several leaders
that a line agrees with, the first by hash of the line is taken; texts and lines of any length are taken whole; an empty
table gives none; other columns, of whatever name, are untouched.
"""

from __future__ import annotations

import re
from zlib import crc32

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubedensity.llm.common import bind, content_key, durable, released, sent, tidy, where_marked, written
from cubedensity.llm.components import components

SHORT = 5
LEAD = 3
LEAST_TEXTS = 3
SHORT_TEXTS = 20
ALIKE = 0.7
BATCH_LINES = 20_000
#: bytes of tokens of one run that a task walks before they are dealt out, and prints that a task remembers
RUN_BYTES = 4_000_000
REMEMBERED = 50_000
#: least hashes of a text that tell its copies, and texts of a template that are walked in one task before their number is cut
SKETCH = 32
HOLDERS = 4096

_FIELD = re.compile(r"[0-9@]|://")
LINES = "_kid {kind}, _kh bigint, leaf bigint, mask bigint, size int, nos array<int>, tokens binary"


class _Prints(dict):
    """32-bit prints of tokens, remembered up to a bound."""

    def __missing__(self, token: str) -> int:
        if len(self) >= REMEMBERED:
            self.clear()
        made = self[token] = crc32(token.encode())
        return made


def tokens_of(line: str) -> list[str]:
    """Lower-cased tokens, with variable fields generalised."""
    tokens = line.lower().split()
    return ["<*>" if _FIELD.search(t) else t for t in tokens] if _FIELD.search(line) else tokens


def _hash(tokens: list[str]) -> int:
    h = xxhash.xxh64_intdigest(" ".join(tokens))
    return h - (1 << 64) if h >> 63 else h


def sketch_of(prints: np.ndarray) -> bytes:
    """The least distinct hashes of the runs of five tokens of a text, in order."""
    n = max(1, len(prints) - 4)
    h = np.zeros(n, np.uint64)
    for k in range(min(5, len(prints))):
        h = (h + prints[k : k + n]) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
    if n > 8 * SKETCH:  # where repeats are few, the least ones need no sort of all
        least = np.unique(np.partition(h, 4 * SKETCH)[: 4 * SKETCH])
        if len(least) >= SKETCH:
            return least[:SKETCH].tobytes()
    return np.unique(h)[:SKETCH].tobytes()


def lines_of(text: str, prints: dict, sketch: bool) -> tuple[list[list], bytes]:
    """([[leaf, generalised line, size, line numbers, prints of the tokens]], sketch if asked for) of a text."""
    found: dict[int, list] = {}
    line_up: list[bytes] = []
    for number, line in enumerate(text.split("\n")):
        tokens = tokens_of(line)
        if not tokens or (len(tokens) < SHORT and set(tokens) == {"<*>"}):
            continue
        mask = _hash(tokens)
        if mask in found:
            found[mask][3].append(number)
        else:
            held = np.fromiter(map(prints.__getitem__, tokens), np.uint32, len(tokens)).tobytes()
            found[mask] = [_hash([str(len(tokens)), *tokens[:LEAD]]), mask, len(tokens), [number], held]
        line_up.append(found[mask][4])
    return list(found.values()), sketch_of(np.frombuffer(b"".join(line_up), np.uint32).astype(np.uint64)) if found and sketch else b""


def line_table(docs: DataFrame, sketch: bool) -> DataFrame:
    """One row for each distinct generalised line of each row of ``docs``, and if asked for one without a line that holds its sketch."""
    kind = dict(docs.dtypes)["doc_id"]

    def run(batches):
        prints = _Prints()
        for batch in batches:
            held: list[tuple] = []
            id_type = batch.schema.field("_kid").type
            for kid, kh, text in zip(batch.column("_kid").to_pylist(), batch.column("_kh").to_pylist(), batch.column("text").to_pylist()):
                lines, least = lines_of(text, prints, sketch)
                held += [(kid, kh, *r) for r in lines]
                if least:
                    held.append((kid, kh, None, None, None, None, least))
                if len(held) >= BATCH_LINES:
                    yield _batch(held, id_type)
                    held = []
            yield _batch(held, id_type)

    return docs.filter("text is not null").select(*content_key(), "text").mapInArrow(released(run), LINES.format(kind=kind))


def _batch(rows, id_type) -> pa.RecordBatch:
    kinds = [id_type, pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.list_(pa.int32()), pa.binary()]
    columns = list(zip(*rows)) if rows else [[]] * len(kinds)
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names=[f.split()[0] for f in LINES.split(", ")])


# templates ---------------------------------------------------------------------------------------------------------
def runs_of(leaf: int, tokens: bytes) -> list[int]:
    """Keys of a line: one for each run of tokens behind the leading ones, one run more than lines may differ in places."""
    n = len(tokens) // 4
    miss = int((1 - ALIKE) * n + 1e-9)
    rest = max(0, n - LEAD)
    cut = [LEAD + rest * i // (miss + 1) for i in range(miss + 2)]
    head = leaf.to_bytes(8, "little", signed=True)
    return [xxhash.xxh64_intdigest(head + i.to_bytes(4, "little") + tokens[4 * a : 4 * b]) >> 1 for i, (a, b) in enumerate(zip(cut, cut[1:]))]


def _runs(batches):
    for batch in batches:
        rows = zip(batch.column("leaf").to_pylist(), batch.column("mask").to_pylist(), batch.column("tokens").to_pylist())
        made = [(key, mask) for leaf, mask, tokens in rows for key in runs_of(leaf, tokens)]
        yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in made], pa.int64()), pa.array([m for _, m in made], pa.int64())], names=["key", "mask"])


def _walk(batches):
    """``(key, u, v)`` of rows that come sorted by key and salt: v agrees with the leader u, or is one (u = v)."""
    at, leaders, names = None, np.zeros((0, 0), np.uint32), []
    for batch in batches:
        keys = list(zip(batch.column("key").to_pylist(), batch.column("salt").to_pylist()))
        masks, held = batch.column("mask").to_pylist(), batch.column("tokens").to_pylist()
        out: list[tuple[int, int, int]] = []
        for key, mask, tokens in zip(keys, masks, held):
            line = np.frombuffer(tokens, np.uint32)
            if key != at:
                at, leaders, names, used = key, np.zeros((8, len(line)), np.uint32), [], 0
            agree = (leaders[:used] == line).sum(axis=1) if used else ()
            near = np.flatnonzero(agree >= ALIKE * len(line) - 1e-9) if used else ()
            if len(near):
                out.append((key[0], names[near[0]], mask))
                continue
            if used == len(leaders):
                leaders = np.concatenate([leaders, np.zeros_like(leaders)])
            leaders[used] = line
            used += 1
            names.append(mask)
            out.append((key[0], mask, mask))
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], pa.int64()) for i in range(3)], names=["key", "u", "v"])


def _leaders(rows: DataFrame) -> DataFrame:
    dealt = rows.repartition("key", "salt").sortWithinPartitions("key", "salt", "mask")
    return dealt.select("key", "salt", "mask", "tokens").mapInArrow(released(_walk), "key bigint, u bigint, v bigint")


def alike(masks: DataFrame) -> DataFrame:
    """``(mask, template)`` of the lines ``masks(leaf, mask, tokens)`` that agree with another."""
    keyed = durable(masks.select("leaf", "mask", "tokens").mapInArrow(released(_runs), "key bigint, mask bigint"))
    sized = keyed.join(masks.select("mask", F.octet_length("tokens").alias("bytes")), "mask").groupBy("key").agg(F.count("*").alias("n"), F.sum("bytes").alias("bytes"))
    shared = durable(sized.filter("n > 1").select("key", F.ceil(F.col("bytes") / RUN_BYTES).alias("salts")))
    members = keyed.join(shared, "key").join(masks.select("mask", "tokens"), "mask")
    first = durable(_leaders(members.withColumn("salt", F.pmod(F.xxhash64("mask"), "salts"))))
    # leaders of a run that was dealt out meet each other
    again = first.filter("u = v").select("key", F.col("u").alias("mask")).join(shared.filter("salts > 1").select("key"), "key", "left_semi")
    second = _leaders(again.join(masks.select("mask", "tokens"), "mask").withColumn("salt", F.lit(0).cast("bigint")))
    del keyed, sized, members
    tidy(masks.sparkSession)
    links = first.select("u", "v").union(second.select("u", "v")).filter("u <> v")
    return components(links).select(F.col("node").alias("mask"), F.col("root").alias("template"))


def _recurs():
    return F.col("texts") >= F.when(F.col("size") < SHORT, SHORT_TEXTS).otherwise(LEAST_TEXTS)


def _recurring(texts: DataFrame, group: DataFrame) -> DataFrame:
    """``(mask, template, size)`` of templates that recur: lines as they stand, and groups of alike lines by distinct row."""
    plain = texts.groupBy("mask").agg(F.sum("n").alias("texts"), F.max("size").alias("size")).filter(_recurs())
    plain = plain.select("mask", F.col("mask").alias("template"), "size")
    mine = texts.join(sent(group), "mask")
    each = mine.groupBy("template", "_kh").agg(F.max("n").alias("n"), F.max("size").alias("size"))  # lines of a leaf have one size
    wide = each.groupBy("template").agg(F.sum("n").alias("texts"), F.max("size").alias("size")).filter(_recurs()).select("template", "size")
    wide = group.join(sent(durable(wide)), "template").select("mask", "template", "size")
    return durable(plain.join(wide.select("mask"), "mask", "left_anti").union(wide))


def _unlike(copies: float):
    """Of rows that come sorted by template and salt, texts that are unlike each other, as many as make a template recur."""

    def run(batches):
        at, held = None, []
        for batch in batches:
            out = []
            for k, (key, size, sketch) in enumerate(zip(zip(batch.column("template").to_pylist(), batch.column("salt").to_pylist()), batch.column("size").to_pylist(), batch.column("sketch").to_pylist())):
                if key != at:
                    at, held = key, []
                if len(held) < (SHORT_TEXTS if size < SHORT else LEAST_TEXTS) and all(resemblance(sketch, x) < copies for x in held):
                    held.append(sketch)
                    out.append(k)
            yield batch.take(pa.array(out, pa.int64()))

    return run


def resemblance(a: bytes, b: bytes) -> float:
    """Similarity of two texts by their least hashes; exact if both are held whole."""
    p, q = np.frombuffer(a, np.uint64), np.frombuffer(b, np.uint64)
    union = np.union1d(p, q)
    if max(len(p), len(q)) == SKETCH:
        union = union[:SKETCH]
    return (np.isin(union, p, assume_unique=True) & np.isin(union, q, assume_unique=True)).sum() / len(union)


def _among_unlike(texts: DataFrame, sketches: DataFrame, found: DataFrame, copies: float) -> DataFrame:
    """``found`` without the templates that too few texts share which are unlike each other."""
    kind = "template bigint, salt bigint, size int, _kh bigint, sketch binary"
    each = texts.select("_kh", "mask").join(sent(found), "mask").groupBy("template", "_kh").agg(F.max("size").alias("size"))
    held = each.join(sketches, "_kh").withColumn("salt", F.lit(0).cast("bigint")).select("template", "salt", "size", "_kh", "sketch")
    # first the texts of a partition, where they are, then in shares of a template's texts, then a template's
    held = durable(held.sortWithinPartitions("template", "salt", "_kh").mapInArrow(released(_unlike(copies)), kind))
    sizes = held.groupBy("template").agg(F.ceil(F.count("*") / HOLDERS).alias("salts"))
    held = held.drop("salt").join(sizes, "template").withColumn("salt", F.pmod("_kh", "salts")).select("template", "salt", "size", "_kh", "sketch")
    for last in (False, True):
        held = held.withColumn("salt", F.lit(0).cast("bigint")) if last else held
        held = held.repartition("template", "salt").sortWithinPartitions("template", "salt", "_kh").mapInArrow(released(_unlike(copies)), kind)
    good = held.groupBy("template").agg(F.count("*").alias("texts"), F.max("size").alias("size")).filter(_recurs()).select("template")
    return durable(found.join(good, "template").select("mask"))


def _counted(lines: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Lines by text, ``(_kh, mask, leaf, size, n)``, and the lines of leaves that could recur, ``(leaf, mask, tokens)``."""
    # a text's lines once, however many rows hold the text
    texts = durable(lines.filter("mask is not null").groupBy("_kh", "mask").agg(F.max("leaf").alias("leaf"), F.max("size").alias("size"), F.count("*").alias("n")))
    leaves = durable(texts.groupBy("leaf").agg(F.sum("n").alias("n")).filter(F.col("n") >= LEAST_TEXTS).select("leaf"))
    tidy(lines.sparkSession)
    # most lines are alone in their leaf and stay where they are; the others are combined before the shuffle
    near, _ = where_marked(lines.filter("mask is not null"), leaves, "leaf")
    masks = near.groupBy("leaf", "mask").agg(F.max("tokens").alias("tokens"))
    return texts, durable(masks.join(leaves, "leaf", "left_semi"))


def recurring(texts: DataFrame, masks: DataFrame, lines: DataFrame, copies: float = 0.0) -> DataFrame:
    """``(mask)`` of all lines of recurring templates, from ``_counted``'s tables; with ``copies``, sketches are taken from ``lines``."""
    found = _recurring(texts, durable(alike(masks)))
    if copies <= 0:
        return found.select("mask")
    sketches = lines.filter("mask is null").groupBy("_kh").agg(F.max("tokens").alias("sketch"))
    return _among_unlike(texts, sketches, found, copies)


def drop_templates(docs: DataFrame, copies: float = 0.0) -> DataFrame:
    """``docs`` with the lines of recurring templates taken out of ``text``; all columns stay. See above for ``copies``."""
    columns = docs.columns
    lines, remove = written(line_table(docs, copies > 0))
    try:
        texts, masks = _counted(lines)
        # the tokens, most of the bytes, are in masks as far as they are still needed
        sketch = F.when(F.col("mask").isNull(), F.col("tokens")).alias("tokens")
        slim, forget = written(lines.select("_kid", "_kh", "nos", "mask", sketch))
    finally:
        remove()
    del lines
    tidy(docs.sparkSession)
    try:
        masks = durable(recurring(texts, masks, slim, copies))
        del texts
        tidy(docs.sparkSession)
        near, _ = where_marked(slim.select("_kid", "_kh", "nos", "mask").filter("mask is not null"), masks, "mask")
        drops = near.join(sent(masks), "mask", "left_semi")
        # repeated rows give repeated lists of the same lines
        drops = durable(drops.groupBy("_kid", "_kh").agg(F.array_distinct(F.flatten(F.collect_set("nos"))).alias("nos")))
    finally:
        forget()
    # the rows travel next: what the lines took on disk goes first
    del near, _
    tidy(docs.sparkSession)
    row = docs.select(F.struct(*columns).alias("row"), *content_key())
    named = drops.select(F.col("_kid").alias("_did"), F.col("_kh").alias("_dh"), "nos")
    held, free = where_marked(row, drops)
    joined = held.join(named, held["_kid"].eqNullSafe(named["_did"]) & (held["_kh"] == named["_dh"]), "left").select("row", "nos")
    joined = joined.union(free.select("row", F.lit(None).cast("array<int>").alias("nos")))

    def kept(parts):
        left = F.array_except(F.sequence(F.lit(0), F.size(parts) - 1), F.col("nos"))
        return F.array_join(F.transform(left, lambda i: F.get(parts, i)), "\n")

    text = F.when(F.col("nos").isNull(), F.col("row.text")).otherwise(bind(F.split(F.col("row.text"), "\n", -1), kept))
    n_chars = {"n_chars": F.length(F.col("_text")).cast(dict(docs.dtypes)["n_chars"])} if "n_chars" in columns else {}
    out = joined.select("row", "nos", text.alias("_text"))
    return out.select(
        *(F.col("_text").alias(c) if c == "text" else F.when(F.col("nos").isNull(), F.col("row.n_chars")).otherwise(n_chars[c]).alias(c) if c in n_chars else F.col(f"row.`{c}`").alias(c) for c in columns)
    )
