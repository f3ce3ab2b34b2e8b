"""Near-duplicates by SimHash fingerprints, found through a covering code of anchors.

Two 64-bit fingerprints that differ in at most four bits are linked.  Sixty-four bits are cut into six blocks,
and a family of block triples is chosen such that, however four differing bits fall on the blocks, one triple
holds at most one of them.  Inside a triple (31 to 33 bits) the anchors are a covering code: the perfect
Hamming code of length 31 (covering radius 1) on the first 31 bits, the other bits kept as they are.  A
fingerprint lives at its anchor within radius 1 and is replicated to every anchor within radius 1 + 1 = 2, so
both ends of every link meet at the home anchor of either.  Fingerprints are compared at each anchor only, all
64 bits; an anchor names about 2^26 places, so unrelated fingerprints seldom meet even among billions.

Copies of a text share one fingerprint row before anything is replicated, and an anchor gives a spanning forest
of its links instead of all pairs, so large groups neither multiply rows nor lose links.

Defined results: null and wordless texts have fingerprint zero and are linked like any other; a null id takes
part (it can be no component id unless every id of its component is null); repeated rows are all returned.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations, combinations_with_replacement

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vertexlog.llm.common import Scratch
from vertexlog.llm.links import LINKS, _as_batches, components, forest

MAX_BITS = 4
BLOCKS = (11, 11, 11, 11, 10, 10)
_STARTS = tuple(int(x) for x in np.cumsum((0, *BLOCKS[:-1])))


def _design() -> tuple[tuple[int, ...], ...]:
    """Fewest-first family of block triples of which one has at most one of any four differing bits."""
    triples = list(combinations(range(len(BLOCKS)), 3))
    falls = [[c.count(i) for i in range(len(BLOCKS))] for c in combinations_with_replacement(range(len(BLOCKS)), MAX_BITS)]
    good = np.array([[sum(f[i] for i in t) <= 1 for f in falls] for t in triples])
    for n in range(1, len(triples) + 1):
        for family in combinations(range(len(triples)), n):
            if good[list(family)].any(axis=0).all():
                return tuple(triples[i] for i in family)
    raise AssertionError


def _syndromes() -> tuple[np.ndarray, np.ndarray]:
    def xors(bits: int, first: int) -> np.ndarray:
        out = np.zeros(1 << bits, np.int64)
        for b in range(bits):
            out[1 << b : 2 << b] = out[: 1 << b] ^ (first + b)
        return out

    return xors(16, 1), xors(15, 17)


def _moves() -> np.ndarray:
    """Row s: what to flip in a word of syndrome s to reach its home anchor, then the others within radius 2."""
    out = np.zeros((32, 16), np.int64)
    for s in range(1, 32):
        pairs = [(1 << (i - 1)) | (1 << ((i ^ s) - 1)) for i in range(1, 32) if i < (i ^ s)]
        out[s] = [1 << (s - 1), *pairs]
    return out


_LOW, _HIGH = _syndromes()
_MOVES = _moves()
_TRIPLES: tuple[tuple[int, ...], ...] | None = None


def triples() -> tuple[tuple[int, ...], ...]:
    global _TRIPLES
    if _TRIPLES is None:
        _TRIPLES = _design()
    return _TRIPLES


def fingerprint(text: bytes | None, shingle: int = 4) -> int:
    """SimHash of a text as a signed 64-bit integer."""
    words = text.lower().split() if text else []
    if not words:
        return 0
    line = b" ".join(words)
    if len(words) <= shingle:
        return int(np.uint64(xxhash.xxh64_intdigest(line, 42)).astype(np.int64))
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    digest = xxhash.xxh64_intdigest
    hashes = np.array([digest(line[a:b], 42) for a, b in zip(starts[: len(words) - shingle + 1].tolist(), ends[shingle - 1 :].tolist(), strict=True)], dtype="<u8")
    votes = np.zeros(64, np.int64)
    for i in range(0, len(hashes), 4096):
        votes += np.unpackbits(hashes[i : i + 4096].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * votes > len(hashes), bitorder="little").view("<u8")[0].astype(np.int64))


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 4) -> DataFrame:
    """(id, fp bigint) for every row."""
    schema = T.StructType([docs.schema[id_col], T.StructField("fp", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made = pa.array([fingerprint(t.as_py(), shingle) for t in batch.column(1)], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), made], names=schema.names)

    return docs.select(F.col(id_col), F.col(text_col).cast("binary").alias("__text")).mapInArrow(run, schema)


def anchors(fps: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(anchor, index into fps, whether it is the fingerprint's home) for all triples."""
    keys, owner, home = [], [], []
    bits, every = fps.view(np.uint64), np.arange(len(fps))
    for k, triple in enumerate(triples()):
        word, width = np.zeros(len(fps), np.int64), 0
        for b in triple:
            word |= ((bits >> np.uint64(_STARTS[b])) & np.uint64((1 << BLOCKS[b]) - 1)).astype(np.int64) << width
            width += BLOCKS[b]
        core = word & 0x7FFFFFFF
        syndrome = _LOW[core & 0xFFFF] ^ _HIGH[core >> 16]
        place = np.int64(k) << 40
        near = word[:, None] ^ _MOVES[syndrome]
        visit = np.ones(near.shape, bool)
        visit[syndrome == 0, 1:] = False
        is_home = np.zeros(near.shape, bool)
        is_home[:, 0] = True
        keys.append(near[visit] | place)
        owner.append(np.broadcast_to(every[:, None], near.shape)[visit])
        home.append(is_home[visit])
        for free in range(31, width):
            keys.append(near[:, 0] ^ (1 << free) | place)
            owner.append(every)
            home.append(np.zeros(len(fps), bool))
    return np.concatenate(keys), np.concatenate(owner), np.concatenate(home)


def _spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        all_fps = batch.column(0).to_numpy(zero_copy_only=False)
        for i in range(0, len(all_fps), 2000):
            fps = np.ascontiguousarray(all_fps[i : i + 2000])
            key, owner, home = anchors(fps)
            yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(fps[owner]), pa.array(home)], names=["anchor", "fp", "home"])


def _near(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count((a ^ b).view(np.uint64)) <= MAX_BITS


def link_group(fps: np.ndarray, home: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Spanning forest of the links between home and visiting fingerprints at one anchor.

    Breadth-first: each fingerprint is compared with those not reached yet, so a dense group costs little more
    than one comparison each.
    """
    left, a, b = np.arange(len(fps)), [], []
    queue: list[int] = []
    while len(left) or queue:
        if not queue:
            queue, left = [int(left[0])], left[1:]
        at = queue.pop()
        hit = _near(fps[left], fps[at]) & (home[left] | home[at])
        if hit.any():
            found = left[hit]
            left = left[~hit]
            queue.extend(found.tolist())
            a.append(fps[found])
            b.append(np.full(len(found), fps[at]))
    none = np.empty(0, np.int64)
    return (np.concatenate(a), np.concatenate(b)) if a else (none, none)


def link_sorted(key: np.ndarray, fps: np.ndarray, home: np.ndarray, small: int = 8) -> tuple[np.ndarray, np.ndarray]:
    """Links among rows sorted by anchor; groups up to ``small`` by shifted comparison, larger ones one by one."""
    edge = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    size = np.diff(np.concatenate([edge, [len(key)]]))
    of = np.repeat(size, size)
    a, b = [], []
    for d in range(1, min(small, int(size.max()))):
        i = np.flatnonzero((key[d:] == key[:-d]) & (of[:-d] <= small) & (home[d:] | home[:-d]))
        i = i[_near(fps[i], fps[i + d])]
        a.append(fps[i])
        b.append(fps[i + d])
    for start, n in zip(edge[size > small], size[size > small], strict=True):
        x, y = link_group(fps[start : start + n], home[start : start + n])
        a.append(x)
        b.append(y)
    none = np.empty(0, np.int64)
    return (np.concatenate(a), np.concatenate(b)) if a else (none, none)


def _compare(batches: Iterator[pa.RecordBatch], limit: int = 500_000) -> Iterator[pa.RecordBatch]:
    """Compare at each anchor; rows come sorted by anchor.  Links of a task leave it as a forest."""
    held: list[tuple[np.ndarray, ...]] = []
    found: list[tuple[np.ndarray, np.ndarray]] = []
    rows = links = 0

    def work(last: bool) -> None:
        nonlocal held, rows, links, found
        key, fps, home = (np.concatenate(x) for x in zip(*held, strict=True))
        cut = len(key) if last else int(np.searchsorted(key, key[-1], "left"))
        if cut:
            a, b = link_sorted(key[:cut], fps[:cut], home[:cut])
            found.append((a, b))
            links += len(a)
        held, rows = [(key[cut:], fps[cut:], home[cut:])], len(key) - cut
        if links > limit:
            a, b = forest(*(np.concatenate(x) for x in zip(*found, strict=True)))
            found, links = [(a, b)], len(a)

    for batch in batches:
        held.append(tuple(batch.column(i).to_numpy(zero_copy_only=False) for i in range(3)))
        rows += batch.num_rows
        if rows > 100_000:
            work(last=False)
    if rows:
        work(last=True)
    if links:
        yield from _as_batches(*forest(*(np.concatenate(x) for x in zip(*found, strict=True))))


def near_duplicates(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", shingle: int = 4) -> DataFrame:
    """(id, fp, component_id) for every row; the component id is the smallest id reachable over links."""
    scratch = Scratch(docs.sparkSession, "simhash")
    each = scratch.keep(fingerprints(docs, id_col, text_col, shingle))
    distinct = scratch.keep(each.groupBy("fp").agg(F.min(id_col).alias("first")))
    placed = distinct.select("fp").mapInArrow(_spread, "anchor bigint, fp bigint, home boolean")
    links = placed.repartition("anchor").sortWithinPartitions("anchor").mapInArrow(_compare, LINKS)
    stars = components(links)
    rooted = distinct.join(stars.withColumnRenamed("u", "fp"), "fp", "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    least = rooted.groupBy("root").agg(F.min("first").alias("component_id"))
    placed_fps = scratch.keep(rooted.join(least, "root").select("fp", "component_id"))
    return each.join(placed_fps, "fp").select(id_col, "fp", "component_id")


def near_duplicate_report(docs: DataFrame, **options: object) -> DataFrame:
    """The contract's columns: id, fingerprint as 16 hex digits, component id."""
    id_col = options.get("id_col", "doc_id")
    found = near_duplicates(docs, **options)
    return found.select(id_col, F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def keep_one_of_each(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", shingle: int = 4) -> DataFrame:
    """The documents without those that have a near-duplicate of smaller id; columns unchanged.

    Rows of equal id are one document: all of them stay or all go.  Rows with a null id stay.
    """
    found = near_duplicates(docs, id_col=id_col, text_col=text_col, shingle=shingle)
    gone = found.where(F.col("component_id") < F.col(id_col)).select(id_col).distinct()
    return docs.join(gone, id_col, "left_anti").select(docs.columns)
