"""Benchmark decontamination with suffix arrays over shards of the training texts.

A shard is a run of documents inside one task, at most ``SHARD_WORDS`` words unless one document is longer. Its
suffix array is sorted to the depth of a window; suffixes that begin with no n-gram of any item can bound no match
and are left out. Every window-long suffix of every item is found by binary search in every shard; hits that follow
each other on one diagonal are joined into the longest verbatim match, with its place in document and item.

Items are handed to the tasks in blocks of a stated size. A benchmark of several blocks takes a pass for each, whose matches
are written before the next begins, so that one block at a time is held, and the few texts with matches meet them at the end.

Inputs: null texts have no words; an item without words never occurs; items of fewer words than a window are one
window; repeated items count once under their id; repeated documents give repeated rows; texts of any length are searched
whole (one that exceeds a shard is a shard of its own); empty tables give no rows or no matches; columns that clash with
those made here are replaced where they are named and untouched otherwise.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubedensity.llm.common import durable, released, where_marked

WINDOW = 10
SHARD_WORDS = 1_000_000
#: characters of items in a block: about 100 MB of windows in the driver and in a worker
BLOCK_CHARS = 4_000_000

#: fixed values: byte classes of a word (ASCII digits and letters, lower-cased, and all non-ASCII bytes)
_FOLD = bytes(
    b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256)
)
MATCH = "struct<item_id:string,doc_start:int,item_start:int,length:int>"


def words_of(text: bytes) -> list[bytes]:
    return text.translate(_FOLD).split()


class ItemIndex:
    """Windows of a block of items, as fixed-width keys to search for."""

    def __init__(self, items: list[tuple[str, str]], window: int):
        self.window = window
        self.vocabulary: dict[bytes, int] = {}
        self.ids: list[str] = []
        parts: list[list[int]] = []
        for item_id, text in items:
            ids = [self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words_of((text or "").encode())]
            if ids:
                self.ids.append(item_id)
                parts.append(ids)
        size = np.array([len(p) for p in parts], np.int64)
        words = np.fromiter((w for p in parts for w in p), np.int64, int(size.sum()))
        begin = np.cumsum(size) - size
        many = np.maximum(1, size - window + 1)
        self.item = np.repeat(np.arange(len(parts)), many)
        self.at = np.arange(int(many.sum())) - np.repeat(np.cumsum(many) - many, many)
        long = np.minimum(size, window)[self.item]  # words of each window
        place = np.arange(window)
        held = place < long[:, None]
        spot = np.minimum((begin[self.item] + self.at)[:, None] + place, max(0, len(words) - 1))
        found = np.where(held, words[spot] if len(words) else 0, 0).astype(">u4")
        keys = np.ascontiguousarray(found).view(f"S{4 * window}").ravel()
        self.low, head, entry = np.unique(keys, return_index=True, return_inverse=True)
        self.sizes = long[head]
        self.high = np.ascontiguousarray(np.where(held[head], found[head], 0xFFFFFFFF).astype(">u4")).view(f"S{4 * window}").ravel()
        order = np.argsort(entry, kind="stable")
        self.item, self.at = self.item[order], self.at[order]
        self.first = np.concatenate([[0], np.cumsum(np.bincount(entry, minlength=len(self.low)))]).astype(np.int64)
        self.gram = min([3, *self.sizes.tolist()])
        base = len(self.vocabulary) + 1
        while base**self.gram >= 1 << 62:
            self.gram -= 1
        self.bits = np.zeros(1 << 22, bool)
        if len(self.low):
            self.bits[self._slot(self._pack(found[head, : self.gram].astype(np.int64).T, base))] = True

    def _pack(self, parts, base: int) -> np.ndarray:
        out = np.zeros(parts.shape[1], np.int64)
        for part in parts:
            out = out * base + part
        return out

    @staticmethod
    def _slot(packed: np.ndarray) -> np.ndarray:
        return (packed.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(42)

    def hits(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(position, item, place in item, words) of every occurrence of a window in the word numbers of a shard."""
        none = (np.zeros(0, np.int64),) * 4
        if not len(self.sizes) or len(ids) < self.gram:
            return none
        n = len(ids) - self.gram + 1
        packed = self._pack(np.stack([ids[k : k + n] for k in range(self.gram)]).astype(np.int64), len(self.vocabulary) + 1)
        starts = np.flatnonzero(self.bits[self._slot(packed)] & (ids[:n] > 0))
        if not len(starts):
            return none
        padded = np.concatenate([ids, np.zeros(self.window, ids.dtype)]).astype(">u4")
        keys = np.ascontiguousarray(padded[starts[:, None] + np.arange(self.window)]).view(f"S{4 * self.window}").ravel()
        order = np.argsort(keys, kind="stable")
        suffixes, keys = starts[order], keys[order]
        left = np.searchsorted(keys, self.low, "left")
        count = np.searchsorted(keys, self.high, "right") - left
        some = np.flatnonzero(count)
        if not len(some):
            return none
        times = count[some]
        window = np.repeat(some, times)
        position = suffixes[np.repeat(left[some] - np.concatenate([[0], np.cumsum(times)[:-1]]), times) + np.arange(times.sum())]
        times = (self.first[1:] - self.first[:-1])[window]
        entry = np.repeat(self.first[window] - np.concatenate([[0], np.cumsum(times)[:-1]]), times) + np.arange(times.sum())
        return np.repeat(position, times), self.item[entry], self.at[entry], np.repeat(self.sizes[window], times)


def joined(position, item, at, size):
    """Join hits of one item that follow each other on a diagonal into maximal matches."""
    if not len(position):
        return position, item, at, size
    order = np.lexsort((position, position - at, item))
    position, item, at, size = position[order], item[order], at[order], size[order]
    new = np.ones(len(position), bool)
    new[1:] = (item[1:] != item[:-1]) | (position[1:] != position[:-1] + 1) | (at[1:] != at[:-1] + 1)
    head = np.flatnonzero(new)
    last = np.append(head[1:], len(position)) - 1
    return position[head], item[head], at[head], position[last] - position[head] + size[head]


def _search(index: ItemIndex, columns: list[str]):
    def run(batches):
        number = type("Numbers", (dict,), {"__missing__": lambda self, w: 0})(index.vocabulary).__getitem__
        empty = np.zeros(1, np.int32)
        for batch in batches:
            texts = pc.cast(batch.column("text"), pa.binary()).to_pylist()
            counts: list[int] = []
            found: list[list[dict]] = [[] for _ in texts]
            shard: list[np.ndarray] = []
            begin: list[int] = []
            size, first = 0, 0

            def close(first=first):
                if not size:
                    return
                offsets = np.array(begin, np.int64)
                position, item, at, length = joined(*index.hits(np.concatenate(shard)))
                doc = np.searchsorted(offsets, position, "right") - 1
                for d, p, i, a, n in zip(doc.tolist(), (position - offsets[doc]).tolist(), item.tolist(), at.tolist(), length.tolist()):
                    found[first + d].append({"item_id": index.ids[i], "doc_start": p, "item_start": a, "length": n})

            for k, text in enumerate(texts):
                words = words_of(text or b"")
                counts.append(len(words))
                begin.append(size)
                shard += [np.fromiter(map(number, words), np.int32, len(words)), empty]
                size += len(words) + 1
                if size >= SHARD_WORDS or k + 1 == len(texts):
                    close(first)
                    shard, begin, size, first = [], [], 0, k + 1
            kept = [batch.column(c) for c in columns]
            yield pa.RecordBatch.from_arrays(
                [*kept, pa.array(counts, pa.int64()), pa.array(found, pa.list_(pa.struct([("item_id", pa.string()), ("doc_start", pa.int32()), ("item_start", pa.int32()), ("length", pa.int32())])))],
                names=[*columns, "_n_words", "_found"],
            )

    return run


#: the bytes of words, as a pattern that counts them
_WORDS = "[^\\x00-\\x2F\\x3A-\\x40\\x5B-\\x60\\x7B-\\x7F]+"


def _pass(docs: DataFrame, items: DataFrame, window: int) -> DataFrame:
    """``docs`` with ``_n_words`` and ``_found``, the matches with a block of items."""
    index = ItemIndex([(r[0], r[1]) for r in items.orderBy("item_id", "text").collect()], window)
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return docs.mapInArrow(released(_search(index, docs.columns)), f"{kinds}, _n_words bigint, _found array<{MATCH}>")


def longest_matches(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """``docs`` with ``n_words`` and ``matches``: all maximal verbatim matches of at least a window (or a whole shorter item).

    ``benchmark(item_id, text)`` is taken in blocks of about ``block_chars`` characters. Columns of ``docs`` named ``n_words``
    or ``matches`` are replaced.
    """
    docs = docs.select(*(c for c in docs.columns if c not in ("n_words", "matches", "_n_words", "_found")))
    items = benchmark.select(F.col("item_id").cast("string").alias("item_id"), "text").filter("text is not null").distinct()
    total = items.agg(F.sum(F.length("text"))).first()[0] or 0
    blocks = max(1, -(-total // block_chars))
    if blocks == 1:
        return _pass(docs, items, window).withColumnsRenamed({"_n_words": "n_words", "_found": "matches"})
    items = durable(items)
    row = docs.select(F.struct(*docs.columns).alias("_row"), F.hash("text").alias("_kid"), F.xxhash64("text").alias("_kh"), "text")
    parts = []
    for block in range(blocks):
        mine = items.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == block)
        found = _pass(row.select("_kid", "_kh", "text"), mine, window).filter(F.size("_found") > 0)
        parts.append(durable(found.select("_kid", "_kh", "_found")))
    every = parts[0]
    for part in parts[1:]:
        every = every.union(part)
    # equal texts have equal matches
    every = durable(every.groupBy("_kid", "_kh").agg(F.flatten(F.collect_set("_found")).alias("matches")))
    held, free = where_marked(row, every)
    none = F.array().cast(f"array<{MATCH}>")
    named = every.select(F.col("_kid").alias("_i"), F.col("_kh").alias("_h"), "matches")
    met = held.join(named, (F.col("_kid") == F.col("_i")) & (F.col("_kh") == F.col("_h")), "left").select("_row", "text", F.coalesce("matches", none).alias("matches"))
    met = met.union(free.select("_row", "text", none.alias("matches")))
    return met.select("_row.*", F.coalesce(F.regexp_count("text", F.lit(_WORDS)), F.lit(0)).cast("bigint").alias("n_words"), "matches")


def hit_words(matches):
    """Words of a document inside any of its matches."""
    spans = F.array_sort(F.transform(matches, lambda m: F.struct(m["doc_start"].alias("s"), (m["doc_start"] + m["length"]).alias("e"))))
    start = F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).alias("end"))
    step = lambda a, x: F.struct((a["n"] + F.greatest(F.lit(0), x["e"] - F.greatest(x["s"], a["end"]))).alias("n"), F.greatest(a["end"], x["e"]).alias("end"))
    return F.aggregate(spans, start, step, lambda a: a["n"])


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """Per document: words, words hit, items that occur, and the digest of their ids."""
    found = longest_matches(docs.select("doc_id", "text"), benchmark, window).drop("text")
    items = F.array_sort(F.array_distinct(F.transform("matches", lambda m: m["item_id"])))
    out = found.withColumn("n_hit", hit_words(F.col("matches"))).withColumn("_items", items)
    return out.select(
        "doc_id",
        "n_words",
        "n_hit",
        F.size("_items").cast("long").alias("n_items"),
        F.sha2(F.array_join("_items", ","), 256).alias("items_sha256"),
        (F.col("n_hit") > 0).alias("contaminated"),
    )


def decontaminate(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """``docs`` without the documents that hold a window of any item; the columns stay as they are."""
    found = longest_matches(docs.select(F.struct(*docs.columns).alias("row"), F.col("text").alias("text")), benchmark, window)
    return found.filter(F.size("matches") == 0).select("row.*")
