"""Benchmark decontamination by Wu-Manber multi-pattern search over words.

Every benchmark text gives windows of ``window`` consecutive words (a shorter text is one window).  All windows
of one length form a pattern set.  A shift table over blocks of two words says how far the search may jump when
a block ends at the current word: a block that no pattern has lets it jump ``length - 1`` words at once, so most
of a clean text is never looked at.  Where the shift is zero, the hash of the last words selects a bucket of
patterns, and comparing the words decides.

Up to ``block_bytes`` of benchmark text the search needs no shuffle: the pattern tables travel to the documents.  A
larger benchmark is cut into blocks of about that size, by the hash of its distinct texts, and every block has a pass
of its own: its tables are built once in a worker, and only one block is broadcast at a time.  A pass writes the hits
of those texts that have any, under a 256-bit hash of the text; spans and items of all passes then come back to the
documents by that hash.  So neither workers nor driver ever hold more than one block.

Defined results: null or wordless text has no words, no hits and is clean; a null benchmark text has no windows;
a null item id is reported as the string ``null``; repeated items count once per id; documents are judged row by
row, so repeated rows get equal results; an empty benchmark hits nothing.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from typing import Any

import pyarrow as pa
from pyspark.core.broadcast import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vertexlog.llm.common import Scratch

_OTHER = bytes(b for b in range(128) if not (48 <= b <= 57 or 97 <= b <= 122))
_TO_SPACE = bytes(32 if b in _OTHER else b for b in range(256))
_BUILT: dict[Any, list] = {}

FOUND = "n_words bigint, spans array<struct<start:bigint,words:bigint>>, items array<string>"
#: What is a word before lower-casing; fixed value.
WORDS = "[^\\x00-\\x2F\\x3A-\\x40\\x5B-\\x60\\x7B-\\x7F]+"


def words_in(text: bytes | None) -> list[bytes]:
    """Lower-cased (A-Z) words: digits, letters a-z and everything beyond ASCII."""
    return text.lower().translate(_TO_SPACE).split() if text else []


class PatternSet:
    """Windows of one length with their shift table and suffix buckets."""

    def __init__(self, length: int) -> None:
        self.length, self.width = length, min(2, length)
        self.tail = min(4, length)
        self.shift: dict[Any, int] = {}
        self.buckets: dict[Any, list[tuple[tuple[bytes, ...], set[str]]]] = {}
        self.reach = length - self.width + 1

    def add(self, window: tuple[bytes, ...], item: str) -> None:
        n, w = self.length, self.width
        for end in range(w, n + 1):
            block = window[end - w : end] if w > 1 else window[end - 1]
            self.shift[block] = min(self.shift.get(block, self.reach), n - end)
        bucket = self.buckets.setdefault(window[-self.tail :], [])
        for known, items in bucket:
            if known == window:
                items.add(item)
                return
        bucket.append((window, {item}))

    def search(self, words: list[bytes]) -> Iterator[tuple[int, set[str]]]:
        """Start and items of every occurrence."""
        n, m, reach, tail = len(words), self.length, self.reach, self.tail
        shift, buckets, at = self.shift.get, self.buckets.get, m - 1
        if self.width == 1:
            for at, word in enumerate(words):
                for _, items in buckets((word,), ()):
                    yield at, items
            return
        while at < n:
            step = shift((words[at - 1], words[at]), reach)
            if step:
                at += step
                continue
            bucket = buckets(tuple(words[at - tail + 1 : at + 1]))
            if bucket:
                here = tuple(words[at - m + 1 : at + 1])
                for window, items in bucket:
                    if window == here:
                        yield at - m + 1, items
            at += 1


def build(rows: list[tuple[str, bytes | None]], window: int) -> list[PatternSet]:
    sets: dict[int, PatternSet] = {}
    for item, text in rows:
        words = words_in(text)
        if not words:
            continue
        length = min(window, len(words))
        into = sets.setdefault(length, PatternSet(length))
        for i in range(len(words) - length + 1):
            into.add(tuple(words[i : i + length]), item)
    return list(sets.values())


def spans_of(words: list[bytes], sets: list[PatternSet]) -> tuple[list[dict[str, int]], list[str]]:
    """Merged spans of hit words and the items found (sorted)."""
    marks, found = None, set()
    for patterns in sets:
        if patterns.length > len(words):
            continue
        for start, items in patterns.search(words):
            if marks is None:
                marks = bytearray(len(words))
            marks[start : start + patterns.length] = b"\x01" * patterns.length
            found |= items
    if marks is None:
        return [], []
    spans, at = [], marks.find(1)
    while at >= 0:
        end = marks.find(0, at)
        end = len(marks) if end < 0 else end
        spans.append({"start": at, "words": end - at})
        at = marks.find(1, end)
    return spans, sorted(found)


def _tables(shared: Broadcast, window: int) -> list[PatternSet]:
    """Tables of a block, for as long as a worker serves that block."""
    key = (shared.id if hasattr(shared, "id") else id(shared), getattr(shared, "_path", None), window)
    if key not in _BUILT:
        _BUILT.clear()
        _BUILT[key] = build(shared.value, window)
    return _BUILT[key]


def _search(docs: DataFrame, shared: Broadcast, window: int, hits_only: bool) -> DataFrame:
    """docs, of which the last column is the text in bytes, with n_words, spans and items in its place."""
    fields = docs.schema.fields[:-1]
    schema = T.StructType([*fields, *T._parse_datatype_string(FOUND).fields])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = [pa.int64(), pa.list_(pa.struct([("start", pa.int64()), ("words", pa.int64())])), pa.list_(pa.string())]
        for batch in batches:
            sets = _tables(shared, window)
            n_words, spans, items, rows = [], [], [], []
            for i, text in enumerate(batch.column(len(fields))):
                words = words_in(text.as_py())
                where, found = spans_of(words, sets) if words else ([], [])
                if where or not hits_only:
                    rows.append(i)
                    n_words.append(len(words))
                    spans.append(where)
                    items.append(found)
            made = [pa.array(v, k) for v, k in zip((n_words, spans, items), kinds, strict=True)]
            yield pa.RecordBatch.from_arrays([*(c.take(pa.array(rows, pa.int64())) for c in batch.columns[:-1]), *made], names=schema.names)

    return docs.mapInArrow(run, schema)


def _items(bench: DataFrame, item_col: str, text_col: str) -> DataFrame:
    return bench.select(F.coalesce(F.col(item_col).cast("string"), F.lit("null")).alias("item"), F.col(text_col).cast("binary").alias("text")).where("text is not null")


def _block(rows: DataFrame) -> Broadcast:
    return rows.sparkSession.sparkContext.broadcast([(r.item, bytes(r.text)) for r in rows.toLocalIterator()])


def _merged(spans: Column) -> Column:
    """Overlapping or touching spans made one."""
    kind = "array<struct<start:bigint,words:bigint>>"

    def step(a: Column, x: Column) -> Column:
        last = F.element_at(a, -1)
        end = F.greatest(last["start"] + last["words"], x["start"] + x["words"])
        joined = F.concat(F.slice(a, F.lit(1), F.size(a) - 1), F.array(F.struct(last["start"].alias("start"), (end - last["start"]).alias("words"))))
        return F.when((F.size(a) > 0) & (F.try_element_at(a, F.lit(-1))["start"] + F.try_element_at(a, F.lit(-1))["words"] >= x["start"]), joined).otherwise(F.array_append(a, x))

    return F.aggregate(F.array_sort(spans), F.array().cast(kind), step)


def _block_by_block(docs: DataFrame, rows: DataFrame, blocks: int, text_col: str, window: int) -> DataFrame:
    """docs with ``__found``, null where no block has a hit, else a struct of n_words, spans and items."""
    scratch, key = Scratch(docs.sparkSession, "hits"), F.sha2(F.col(text_col).cast("binary"), 256)
    known = scratch.keep(rows.groupBy("text").agg(F.collect_set("item").alias("items")).select("text", F.explode("items").alias("item")))
    passes = []
    for i in range(blocks):
        shared = _block(known.where(F.pmod(F.xxhash64("text"), F.lit(blocks)) == i))
        found = _search(docs.select(key.alias("__key"), F.col(text_col).cast("binary").alias("__text")), shared, window, hits_only=True)
        passes.append(scratch.keep(found.groupBy("__key").agg(F.first(F.struct("n_words", "spans", "items")).alias("f"))))
        shared.destroy()
    every = reduce(DataFrame.unionByName, passes)
    hits = every.groupBy("__key").agg(F.max("f.n_words").alias("n_words"), F.flatten(F.collect_list("f.spans")).alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("f.items")))).alias("items"))
    by_key = hits.select("__key", F.struct("n_words", _merged(F.col("spans")).alias("spans"), "items").alias("__found"))
    return docs.withColumn("__key", key).join(by_key, "__key", "left").drop("__key")


def _blocks_of(rows: DataFrame, block_bytes: int) -> int:
    return max(1, -(-(rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0) // block_bytes))


def _count_words(docs: DataFrame, text_col: str) -> Column:
    return F.size(F.regexp_extract_all(F.coalesce(F.col(text_col), F.lit("")), F.lit(WORDS), F.lit(0))).cast("bigint")


def find_occurrences(docs: DataFrame, bench: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", window: int = 13, block_bytes: int = 32 << 20) -> DataFrame:
    """One row per document: its id, ``n_words``, ``n_hit``, ``items`` and the ``spans`` of hit words."""
    rows = _items(bench, item_col, item_text_col)
    blocks = _blocks_of(rows, block_bytes)
    if blocks == 1:
        found = _search(docs.select(F.col(id_col), F.col(text_col).cast("binary").alias("__text")), _block(rows), window, hits_only=False)
    else:
        joined = _block_by_block(docs.select(id_col, text_col), rows, blocks, text_col, window)
        none = F.array().cast("array<struct<start:bigint,words:bigint>>")
        words = F.coalesce("__found.n_words", _count_words(docs, text_col))
        found = joined.select(id_col, words.alias("n_words"), F.coalesce("__found.spans", none).alias("spans"), F.coalesce("__found.items", F.array().cast("array<string>")).alias("items"))
    n_hit = F.aggregate("spans", F.lit(0).cast("bigint"), lambda n, x: n + x["words"])
    return found.select(id_col, "n_words", n_hit.alias("n_hit"), "items", "spans")


def remove_contaminated(docs: DataFrame, bench: DataFrame, *, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", window: int = 13, one_in: int = 20, block_bytes: int = 32 << 20) -> DataFrame:
    """The documents of which less than one word in ``one_in`` lies in a benchmark window; columns unchanged."""
    rows = _items(bench, item_col, item_text_col)
    blocks = _blocks_of(rows, block_bytes)
    if blocks > 1:
        joined = _block_by_block(docs, rows, blocks, text_col, window)
        n_hit = F.aggregate("__found.spans", F.lit(0).cast("bigint"), lambda n, x: n + x["words"])
        return joined.where(F.col("__found").isNull() | (one_in * n_hit < F.col("__found.n_words"))).select(docs.columns)
    shared, at = _block(rows), docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets, keep = _tables(shared, window), []
            for text in batch.column(at).cast(pa.binary()):
                words = words_in(text.as_py())
                hit = sum(x["words"] for x in spans_of(words, sets)[0]) if words else 0
                keep.append(not (hit and one_in * hit >= len(words)))
            yield batch.filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def contamination_report(docs: DataFrame, bench: DataFrame, **options: Any) -> DataFrame:
    """The digest of each document that the contract asks for, and its number of hit spans."""
    id_col = options.get("id_col", "doc_id")
    found = find_occurrences(docs, bench, **options)
    hit = (F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words"))
    return found.select(id_col, "n_words", "n_hit", F.size("items").cast("bigint").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), hit.alias("contaminated"), F.size("spans").cast("bigint").alias("n_spans"))
