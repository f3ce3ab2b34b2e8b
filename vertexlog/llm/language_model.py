"""Scoring by a hashed maximum-entropy model of words with a class-factored softmax.

P(word | context) = P(class | context) * P(word | class).  The most frequent words are classes of their own; words that
occur in the same documents form further classes; the rest falls into classes by hash, and one class stands for all
words that training never saw.  The class factor is a softmax over hashed features of the context: the previous word,
the classes of the previous two words, and the word before the previous one (skip).  The word factor is the word's
smoothed share of its class, so context moves it by moving between the classes of one vocabulary and another's.

Training: word counts over all training texts come from one pass and one aggregate.  How often the ``anchors`` most
frequent words share a document sorts these into groups; every document then belongs to the group it has most of, and
every word that occurs often enough to the group where it occurs most, both over all training texts.  The class weights
are trained in ``rounds`` passes, each over another part of the training texts, all of them in the end: every task
takes gradient steps from the common weights and the changes are averaged by tokens.  Scoring is one pass of sparse
numpy batches.

Sizes: counts grow with the input, as do the words with a class of their own choice (up to ``grouped`` of them, those of
the highest counts) and the buckets of features (a 256th of the distinct words, 4,096 to ``most_buckets``).  Counts
reach the documents by broadcast while there are at most ``broadcast_types`` distinct words, which is 16 bytes each at
the driver, 128 MB at most by default; beyond that they are joined to the words of each document, all but the most
frequent, which travel with the model, so that no join key has more than a few rows in a million.  Scores are equal.

Defined results: a null text is the end token alone; without training texts all words are unknown; repeated
rows count as often as they occur; a null id is trained on and not held out.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vertexlog.llm.common import Scratch
from vertexlog.llm.language_id import in_fold

#: Hashes of the end token and of the place before a text; fixed values, no word of any text has them.
END, BEGIN = 1, 2
RESULT = "held_out boolean, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double"
_LOG10 = np.log(10.0)


@dataclass(frozen=True)
class Shape:
    top: int = 15
    groups: int = 12
    hashed: int = 4
    buckets: int = 4096
    features: int = 3

    @property
    def classes(self) -> int:
        return self.top + self.groups + self.hashed + 1


def coded(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of the kinds of words, the kind of each token of all texts one after another with their ends, and the tokens of each text."""
    words = pc.ascii_split_whitespace(pc.ascii_lower(pc.fill_null(texts, "")))
    coded = words.flatten().dictionary_encode()
    sizes = pc.list_value_length(words).to_numpy(zero_copy_only=False)
    digest = xxhash.xxh64_intdigest
    hashes = np.array([digest(w, 7) | 4 if w else 0 for w in coded.dictionary.cast(pa.binary()).to_pylist()], np.uint64).view(np.int64)
    tokens = coded.indices.to_numpy(zero_copy_only=False)
    empty = np.flatnonzero(hashes == 0)
    if len(empty):  # the cut leaves an empty word at either end of a text
        real = tokens != empty[0]
        sizes = np.bincount(np.repeat(np.arange(len(sizes)), sizes)[real], minlength=len(sizes))
        tokens = tokens[real]
    n = sizes.astype(np.int64) + 1
    at = np.full(int(n.sum()), len(hashes), np.int64)
    place = np.ones(len(at), bool)
    place[np.cumsum(n) - 1] = False
    at[place] = tokens
    return np.append(hashes, np.int64(END)), at, n


def encode(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes of all texts one after another, each with its end token, and the tokens of each text."""
    kinds, at, n = coded(texts)
    return kinds[at], n


def parts(batch: pa.RecordBatch, column: int, limit: int = 3_000_000) -> Iterator[pa.RecordBatch]:
    """A batch in runs of rows whose texts have about ``limit`` bytes together."""
    size = np.nan_to_num(pc.binary_length(batch.column(column)).to_numpy(zero_copy_only=False).astype(float))
    run = (np.cumsum(size) // limit).astype(np.int64)
    start = 0
    for end in [*(np.flatnonzero(np.diff(run)) + 1).tolist(), batch.num_rows]:
        if end > start:
            yield batch.slice(start, end - start)
        start = end


def tally(batches: Iterator[pa.RecordBatch], most: int = 1_500_000) -> Iterator[pa.RecordBatch]:
    """Counts of word hashes of a task's texts, folded whenever more than ``most`` are held."""
    held_h, held_n, size = [], [], 0

    def fold() -> tuple[np.ndarray, np.ndarray]:
        h, at = np.unique(np.concatenate(held_h), return_inverse=True)
        return h, np.bincount(at, np.concatenate(held_n), len(h)).astype(np.int64)

    for batch in batches:
        for part in parts(batch, 0):
            h, at, _ = coded(part.column(0))
            n = np.bincount(at, minlength=len(h))
            h, n = h[n > 0], n[n > 0]
            held_h.append(h)
            held_n.append(n)
            size += len(h)
            if size > most:
                h, n = fold()
                if len(h) > most // 2:
                    yield pa.RecordBatch.from_arrays([pa.array(h), pa.array(n)], names=["h", "n"])
                    held_h, held_n, size = [], [], 0
                else:
                    held_h, held_n, size = [h], [n], len(h)
    if held_h:
        h, n = fold()
        for i in range(0, len(h), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(h[i : i + 100_000]), pa.array(n[i : i + 100_000])], names=["h", "n"])


class Classes:
    """Class of each word hash: its own, that of its group, or one by hash."""

    def __init__(self, words: np.ndarray, numbers: np.ndarray, shape: Shape) -> None:
        order = np.argsort(words)
        self.shape, self.sorted, self.number = shape, words[order], numbers[order].astype(np.int8)

    def of(self, kinds: np.ndarray) -> np.ndarray:
        """Class of each hash; worth calling for distinct ones."""
        out = self.shape.top + self.shape.groups + ((kinds >> 3) & np.int64(self.shape.hashed - 1))
        if len(self.sorted):
            place = np.minimum(np.searchsorted(self.sorted, kinds), len(self.sorted) - 1)
            out = np.where(self.sorted[place] == kinds, self.number[place], out)
        return out


def contexts(h: np.ndarray, n: np.ndarray, group: np.ndarray, shape: Shape) -> np.ndarray:
    """(features x tokens) buckets of previous word, classes of the previous two, and skipped word."""

    def before(x: np.ndarray, start: int) -> tuple[np.ndarray, np.ndarray]:
        one, two = np.empty_like(x), np.empty_like(x)
        one[1:], two[2:] = x[:-1], x[:-2]
        one[first] = two[first] = two[second] = start
        return one, two

    first = np.cumsum(n) - n
    second = (first + 1)[n > 1]
    one, two = before(h, BEGIN)
    a, b = before(group, shape.classes)
    mix = lambda x, m: ((x.view(np.uint64) * np.uint64(m)) >> np.uint64(65 - int(shape.buckets).bit_length())).astype(np.int64)
    return np.stack([mix(one, 0xD6E8FEB86659FD93), (a * (shape.classes + 1) + b) % shape.buckets, mix(two, 0xE7037ED1A0B428DB)])


def together(docs: DataFrame, anchors: np.ndarray) -> np.ndarray:
    """In how many texts each two anchors occur together; on the diagonal, in how many each occurs."""
    k = len(anchors)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        met = np.zeros((k, k))
        for batch in batches:
            for part in parts(batch, 0):
                has = times_of(*coded(part.column(0)), anchors) > 0
                met += has.T.astype(float) @ has.astype(float)
        i, j = np.indices((k, k)).reshape(2, -1)
        yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(j), pa.array(met.ravel())], names=["i", "j", "n"])

    out = np.zeros((k, k))
    for r in docs.mapInArrow(run, "i bigint, j bigint, n double").groupBy("i", "j").agg(F.sum("n").alias("n")).collect():
        out[r["i"], r["j"]] = r["n"]
    return out


def times_of(kinds: np.ndarray, at: np.ndarray, n: np.ndarray, anchors: np.ndarray) -> np.ndarray:
    """(texts x anchors) counts."""
    order = np.argsort(anchors)
    place = np.minimum(np.searchsorted(anchors[order], kinds), len(anchors) - 1)
    which = np.where(anchors[order][place] == kinds, order[place], -1)[at]
    hit = np.flatnonzero(which >= 0)
    owner = np.repeat(np.arange(len(n)), n)[hit]
    flat = np.bincount(owner * len(anchors) + which[hit], minlength=len(n) * len(anchors))
    return flat.reshape(len(n), len(anchors))


def grouped_anchors(met: np.ndarray, groups: int) -> np.ndarray:
    """Group of each anchor: those merge that occur together more often than by chance, on average of all pairs."""
    k = len(met)
    if not k:
        return np.zeros(0, int)
    share = np.diag(met) + 0.5
    near = np.log((met + 0.1) * max(met.max(), 1.0) / np.outer(share, share))
    members = [[i] for i in range(k)]
    while len(members) > 1:
        close = np.array([[near[np.ix_(a, b)].mean() if a is not b else -np.inf for b in members] for a in members])
        i, j = divmod(int(close.argmax()), len(members))
        if len(members) <= groups and close[i, j] <= 0:
            break
        members[min(i, j)] += members[max(i, j)]
        del members[max(i, j)]
    out = np.zeros(k, int)
    for g, own in enumerate(members):
        out[own] = g
    return out


def words_by_group(docs: DataFrame, anchors: np.ndarray, of: np.ndarray, total: np.ndarray) -> DataFrame:
    """(h, g, n): how often each word occurs in texts of each group, a text's group being the one it has most of."""
    groups = int(of.max()) + 1
    member = np.zeros((len(anchors), groups))
    member[np.arange(len(anchors)), of] = 1
    usual = total @ member

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in parts(batch, 0):
                kinds, at, n = coded(part.column(0))
                group = ((times_of(kinds, at, n, anchors) @ member) / usual).argmax(axis=1)
                times = np.bincount(at * groups + np.repeat(group, n), minlength=len(kinds) * groups)
                key = np.flatnonzero(times)
                yield pa.RecordBatch.from_arrays([pa.array(kinds[key // groups]), pa.array(key % groups), pa.array(times[key])], names=["h", "g", "n"])

    return docs.mapInArrow(run, "h bigint, g bigint, n bigint").groupBy("h", "g").agg(F.sum("n").alias("n"))


def choose_classes(docs: DataFrame, counts: DataFrame, *, shape: Shape, anchors: int, grouped: int) -> Classes:
    """Classes from training texts (one column) and their word counts."""
    best = counts.where(F.col("h") != END).orderBy(F.desc("n"), "h").limit(max(anchors, shape.top)).collect()
    h, n = np.array([r["h"] for r in best], np.int64), np.array([r["n"] for r in best], float)
    words, numbers = h[: shape.top], np.arange(min(shape.top, len(h)))
    h, n = h[:anchors], n[:anchors]
    if not len(h):
        return Classes(words, numbers, shape)
    of = grouped_anchors(together(docs, h), shape.groups)
    sizes = counts.groupBy("n").agg(F.count("*").alias("types")).where("n > 1").orderBy(F.desc("n")).toLocalIterator()
    least, held = None, 0
    for r in sizes:  # words of the highest counts, as many as may have a group
        held += r["types"]
        if held > grouped:
            break
        least = r["n"]
    if least is None:
        return Classes(words, numbers, shape)
    frequent = counts.where((F.col("n") >= least) & ~F.col("h").isin([END, *map(int, words)])).select("h")
    shares = words_by_group(docs, h, of, n).join(frequent, "h", "left_semi")
    table = shares.groupBy("h").agg(F.max_by("g", F.struct("n", -F.col("g"))).alias("g")).toArrow()
    number = table["g"].to_numpy() + shape.top
    return Classes(np.concatenate([words, table["h"].to_numpy()]), np.concatenate([numbers, number]), shape)


def class_totals(counts: DataFrame, classes: Classes) -> np.ndarray:
    """Smoothed tokens of each class."""
    shared, size = counts.sparkSession.sparkContext.broadcast(classes), classes.shape.classes

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(size)
        for batch in batches:
            total += np.bincount(shared.value.of(batch.column(0).to_numpy()), batch.column(1).to_numpy() + 0.5, size)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(size)), pa.array(total)], names=["k", "t"])

    out = np.full(size, 0.5)
    for r in counts.select("h", "n").mapInArrow(run, "k bigint, t double").groupBy("k").agg(F.sum("t").alias("t")).collect():
        out[r["k"]] = max(r["t"], 0.5)
    return out


def powers(bias: np.ndarray, weights: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each token the exponents of all classes, less the same number for all, their powers of e, and the sum of these."""
    # places are all within bounds; numpy takes rows several times faster if it need not raise
    z = bias + np.take(weights[0], at[0], axis=0, mode="clip")
    for k in range(1, len(weights)):
        z += np.take(weights[k], at[k], axis=0, mode="clip")
    high = z.max(initial=-np.inf)
    z -= high if high - z.min(initial=np.inf) < 60 else z.max(axis=1, keepdims=True)  # a common shift does where no power vanishes
    e = np.exp(z)
    return z, e, np.einsum("ij->i", e)


def log_softmax(bias: np.ndarray, weights: np.ndarray, at: np.ndarray) -> np.ndarray:
    z, _, total = powers(bias, weights, at)
    return z - np.log(total)[:, None]


def descend(bias: np.ndarray, weights: np.ndarray, squares: np.ndarray, at: np.ndarray, target: np.ndarray, rate: float) -> None:
    """One adaptive gradient step on a batch, in place; the unknown class keeps its bias."""
    _, g, total = powers(bias, weights, at)
    g /= total[:, None]
    g[np.arange(len(target)), target] -= 1
    g[:, -1] = 0
    for k in range(len(weights)):
        key = at[k].astype(np.uint16) if weights.shape[1] <= 1 << 16 else at[k]  # short keys are sorted by their digits
        order = np.argsort(key, kind="stable")
        bucket = at[k][order]
        start = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]]))
        total = np.add.reduceat(np.take(g, order, axis=0, mode="clip"), start, axis=0)
        b = bucket[start]
        squares[k, b] += total * total
        weights[k, b] -= rate * total / np.sqrt(squares[k, b] + 1.0)


def train(docs: DataFrame, text_col: str, bias: np.ndarray, classes: Classes, shape: Shape, turn: Column, rounds: int, rate: float, batch_tokens: int = 32_768) -> np.ndarray:
    """Weights (features x buckets x classes) after averaging each round's gradient steps."""
    weights = np.zeros((shape.features, shape.buckets, shape.classes), np.float32)
    columns = ["place int", "tokens bigint", *(f"w{c} float" for c in range(shape.classes))]
    for r in range(rounds):
        shared = docs.sparkSession.sparkContext.broadcast((bias, weights, classes))

        def run(batches: Iterator[pa.RecordBatch], shared: object = shared) -> Iterator[pa.RecordBatch]:
            bias, start, classes = shared.value
            own, squares, seen = start.copy(), np.zeros_like(start), 0
            for batch in batches:
                for part in parts(batch, 0):
                    kinds, at, n = coded(part.column(0))
                    h, target = kinds[at], classes.of(kinds)[at]
                    at = contexts(h, n, target, shape)
                    for i in range(0, len(h), batch_tokens):
                        descend(bias, own, squares, at[:, i : i + batch_tokens], target[i : i + batch_tokens], rate)
                    seen += len(h)
            if seen:
                change = (own - start).reshape(-1, shape.classes)
                moved = np.flatnonzero(np.any(change, axis=1)).astype(np.int32)
                made = [pa.array(moved), pa.array(np.full(len(moved), seen)), *(pa.array(change[moved, c] * np.float32(seen)) for c in range(shape.classes))]
                yield pa.RecordBatch.from_arrays(made, names=[c.split()[0] for c in columns])

        changes = docs.where(turn == r).select(text_col).mapInArrow(run, ", ".join(columns))
        summed = changes.groupBy("place").agg(F.sum("tokens").alias("t"), *(F.sum(f"w{c}").alias(f"w{c}") for c in range(shape.classes))).toArrow()
        if summed.num_rows:
            place = summed["place"].to_numpy()
            change = np.stack([summed[f"w{c}"].to_numpy() for c in range(shape.classes)], axis=1) / summed["t"].to_numpy()[:, None]
            weights.reshape(-1, shape.classes)[place] += change.astype(np.float32)
        shared.unpersist()
    return weights


@dataclass
class Model:
    """What scoring needs besides the counts of rarer words."""

    bias: np.ndarray
    weights: np.ndarray
    classes: Classes
    totals: np.ndarray
    tokens: int
    types: int
    shape: Shape

    def base(self, c: np.ndarray) -> np.ndarray:
        return np.log10((c + 0.5) / (self.tokens + 0.5 * (self.types + 1)))

    def class_part(self, h: np.ndarray, n: np.ndarray, known: np.ndarray, group: np.ndarray) -> np.ndarray:
        """log10 P(class | context) summed for each text."""
        at, out = contexts(h, n, known, self.shape), np.empty(len(h))
        for i in range(0, len(h), 32_768):
            z, _, total = powers(self.bias, self.weights, at[:, i : i + 32_768])
            g = group[i : i + 32_768]
            out[i : i + 32_768] = z[np.arange(len(g)), g] - np.log(total)
        return np.add.reduceat(out, np.cumsum(n) - n) / _LOG10

    def score(self, h: np.ndarray, n: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Known tokens, base score and score of each text, from the count of every token."""
        return self.score_coded(h, np.arange(len(h)), n, c)

    def score_coded(self, kinds: np.ndarray, at: np.ndarray, n: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The same from the count of every kind of token."""
        own = self.classes.of(kinds)
        group = np.where(c > 0, own, self.shape.classes - 1)
        word = np.where(c > 0, np.log10((c + 0.5) / self.totals[group]), 0.0)
        first = np.cumsum(n) - n
        total = lambda x: np.add.reduceat(x[at], first)
        return total((c > 0).astype(np.int64)), total(self.base(c)), total(word) + self.class_part(kinds[at], n, own[at], group[at])


def fit(docs: DataFrame, counts: DataFrame, *, text_col: str, turn: Column, shape: Shape, rounds: int, rate: float, anchors: int, grouped: int, most_buckets: int) -> Model:
    """Model from training texts and their word counts (h, n)."""
    whole = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    shape = replace(shape, buckets=min(most_buckets, max(shape.buckets, 1 << max(0, whole[1] // 256).bit_length())))
    classes = choose_classes(docs.select(text_col), counts, shape=shape, anchors=anchors, grouped=grouped)
    totals = class_totals(counts, classes)
    bias = np.log(totals / totals.sum()).astype(np.float32)
    weights = train(docs, text_col, bias, classes, shape, turn, rounds, rate) if whole[0] else np.zeros((shape.features, shape.buckets, shape.classes), np.float32)
    return Model(bias, weights, classes, totals, whole[0], whole[1], shape)


def score_texts(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", folds: int = 5, fold: int = 1, rounds: int = 2, rate: float = 0.1, shape: Shape = Shape(), anchors: int = 48, grouped: int = 2_000_000, most_buckets: int = 1 << 15, broadcast_types: int = 8_000_000, frequent: int = 4096) -> DataFrame:  # noqa: B008
    """(id, held_out, n_tokens, n_known, train_tokens, base_score, score) for every row."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "words")
    source = docs.select(F.col(id_col), in_fold(F.col(id_col), folds, fold).alias("held_out"), F.col(text_col).alias("__text"))
    learn = source.where("not held_out")
    counts = scratch.keep(learn.select("__text").mapInArrow(tally, "h bigint, n bigint").groupBy("h").agg(F.sum("n").alias("n")))
    turn = F.pmod(F.xxhash64(F.col(id_col), F.lit(11)), F.lit(rounds))
    model = fit(learn, counts, text_col="__text", turn=turn, shape=shape, rounds=rounds, rate=rate, anchors=anchors, grouped=grouped, most_buckets=most_buckets)
    schema = T.StructType([docs.schema[id_col], *T._parse_datatype_string(RESULT).fields])
    if model.types <= broadcast_types:
        return _by_broadcast(source, counts, model, schema)
    return _by_join(scratch.keep(source.withColumn("__row", F.monotonically_increasing_id())), counts, model, schema, frequent)


def _rows(batch: pa.RecordBatch, n: np.ndarray, model: Model, found: tuple[np.ndarray, ...], names: list[str]) -> pa.RecordBatch:
    known, base, score = found
    made = [pa.array(n), pa.array(known), pa.array(np.full(len(n), model.tokens)), pa.array(base), pa.array(score)]
    return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *made], names=names)


def _by_broadcast(source: DataFrame, counts: DataFrame, model: Model, schema: T.StructType) -> DataFrame:
    table = counts.toArrow()
    h, c = table["h"].to_numpy(), table["n"].to_numpy().astype(np.float64 if model.tokens >= 1 << 31 else np.int32)
    order = np.argsort(h)
    shared = source.sparkSession.sparkContext.broadcast((model, h[order], c[order]))
    del table, h, c, order

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, known, times = shared.value
        for batch in batches:
            for part in parts(batch, 2):
                kinds, at, n = coded(part.column(2))
                c = np.zeros(len(kinds))
                if len(known):
                    place = np.minimum(np.searchsorted(known, kinds), len(known) - 1)
                    c = np.where(known[place] == kinds, times[place], 0).astype(float)
                yield _rows(part, n, model, model.score_coded(kinds, at, n, c), schema.names)

    return source.mapInArrow(run, schema)


def _by_join(source: DataFrame, counts: DataFrame, model: Model, schema: T.StructType, frequent: int) -> DataFrame:
    """Counts are joined to the distinct words of each document and come back as a list beside its text.

    The ``frequent`` commonest words stay out of the join: theirs would be its hot keys, and they come with the model.
    """
    best = counts.orderBy(F.desc("n"), "h").limit(frequent).toArrow()
    order = np.argsort(best["h"].to_numpy())
    common_h, common_n = best["h"].to_numpy()[order], best["n"].to_numpy()[order]
    shared = source.sparkSession.sparkContext.broadcast((model, common_h, common_n))

    def words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in parts(batch, 1):
                h, n = encode(part.column(1))
                rare = ~np.isin(h, shared.value[1])
                pair = np.unique(np.stack([np.repeat(np.arange(len(n)), n)[rare], h[rare]]), axis=1)
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(pair[0])), pa.array(pair[1])], names=["__row", "h"])

    used = source.select("__row", "__text").mapInArrow(words, "__row bigint, h bigint").join(counts, "h")
    lists = used.groupBy("__row").agg(F.sort_array(F.collect_list(F.struct("h", "n"))).alias("c"))
    joined = source.join(lists, "__row", "left").select(*(c for c in source.columns if c != "__row"), F.col("c.h").alias("__h"), F.col("c.n").alias("__n"))

    def look(known: np.ndarray, times: np.ndarray, h: np.ndarray) -> np.ndarray:
        if not len(known):
            return np.zeros(len(h))
        place = np.minimum(np.searchsorted(known, h), len(known) - 1)
        return np.where(known[place] == h, times[place], 0).astype(float)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, common_h, common_n = shared.value
        for batch in batches:
            for part in parts(batch, 2):
                h, n = encode(part.column(2))
                c, ends = look(common_h, common_n, h), np.cumsum(n)
                for i, end in enumerate(ends.tolist()):
                    known = np.array(part.column(3)[i].as_py() or [], np.int64)
                    if len(known):
                        c[end - n[i] : end] += look(known, np.array(part.column(4)[i].as_py(), float), h[end - n[i] : end])
                yield _rows(part, n, model, model.score(h, n, c), schema.names)

    return joined.mapInArrow(run, schema)
