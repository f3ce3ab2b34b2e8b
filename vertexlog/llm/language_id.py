"""Language identification by cross-parsing against suffix automata of labelled text.

For each language an automaton of all substrings of a bounded sample of its labelled texts is built.  A text is
cut, against each automaton, into the longest phrases that occur in that language's sample.  The language that
needs the fewest phrases, weighted by the logarithm of its sample's length, wins.

Every language has an alphabet of its own, of all letters of its sample: the commonest have a place in its transition
table, the moves of the others are looked up in a sorted list.  A letter that the sample lacks always ends a phrase;
everything that is no letter is one symbol.  Every labelled language is learned.  Automata are kept as sorted lists of
moves, a few hundred kilobytes each, and only the one that is being parsed against is unfolded into a table.

Texts are parsed whole, in segments of ``segment`` characters so that many are parsed in step by table lookups;
a phrase ends at a segment's end.  Only the sample travels: at most twice ``sample_rows`` texts and ``sample_chars``
characters of each language.  Every other step is a pass without a shuffle.

Defined results: a null text or one without letters (by Unicode category, in all planes) is ``und`` with score 0, as is
everything if nothing is labelled; ties go to the language first in order; with one language the score is 1; repeated
rows get equal results; a null id is neither held out nor learned from; more than ``most_languages`` different labels
are an error, since such labels name no languages.
"""

from __future__ import annotations

import unicodedata
from collections.abc import Iterator
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

RESULT = "held_out boolean, lang_pred string, score double"
UNKNOWN = "und"
_BUILT: dict[Any, CrossParser] = {}


class Automaton:
    """Suffix automaton over small integers."""

    def __init__(self, symbols: list[int]) -> None:
        self.next: list[dict[int, int]] = [{}]
        link, length, last = [-1], [0], 0
        for c in symbols:
            now = len(self.next)
            self.next.append({})
            link.append(0)
            length.append(length[last] + 1)
            p = last
            while p >= 0 and c not in self.next[p]:
                self.next[p][c] = now
                p = link[p]
            if p >= 0:
                q = self.next[p][c]
                if length[q] == length[p] + 1:
                    link[now] = q
                else:
                    twin = len(self.next)
                    self.next.append(dict(self.next[q]))
                    link.append(link[q])
                    length.append(length[p] + 1)
                    while p >= 0 and self.next[p].get(c) == q:
                        self.next[p][c] = twin
                        p = link[p]
                    link[q] = link[now] = twin
            last = now

    def moves(self) -> tuple[np.ndarray, np.ndarray]:
        """(state << 32 | symbol, next state) of all moves, sorted."""
        keys = np.array([s << 32 | c for s, out in enumerate(self.next) for c in out], np.int64)
        to = np.array([t for out in self.next for t in out.values()], np.int32)
        order = np.argsort(keys)
        return keys[order], to[order]


#: Symbols of every alphabet: padding, no letter, a letter that the sample lacks; letters follow by frequency.
PAD, OTHER, FOREIGN, FIRST = 0, 1, 2, 3


class Language:
    """One language's alphabet and automaton, small while it is not in use."""

    def __init__(self, sample: str, letter: np.ndarray, lower: np.ndarray, width: int = 64) -> None:
        codes = lower[_codes(sample)]
        kinds, times = np.unique(codes[letter[codes]], return_counts=True)
        self.letters, self.width = kinds[np.lexsort((kinds, -times))], width
        symbols = self._symbols(letter, lower)[_codes(sample)]
        built = Automaton(symbols.tolist())
        self.states, (self.keys, self.to) = len(built.next), built.moves()
        self.weight = float(np.log2(max(2, len(symbols))))

    def _symbols(self, letter: np.ndarray, lower: np.ndarray) -> np.ndarray:
        """Symbol of every code point."""
        small = np.where(letter, FOREIGN, OTHER).astype(np.int32)
        small[self.letters] = np.arange(FIRST, FIRST + len(self.letters), dtype=np.int32)
        return np.where(letter, small[lower], OTHER).astype(np.int32)

    def unfold(self, letter: np.ndarray, lower: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Symbols by code point, and a flat table [state * width + symbol] of the commonest symbols' moves.

        The table gives the next state, or ~state after a phrase break; padding stays where it is.
        """
        symbol, from_state = self.keys & 0xFFFFFFFF, self.keys >> 32
        near = symbol < self.width
        root = np.zeros(self.width, np.int32)
        first = near & (from_state == 0)
        root[symbol[first]] = self.to[first]
        table = np.empty((self.states, self.width), np.int32)
        table[:] = ~root
        table[from_state[near], symbol[near]] = self.to[near]
        table[:, PAD] = np.arange(self.states)
        return self._symbols(letter, lower), table.ravel()

    def rare(self, state: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        """Moves by symbols beyond the table, in the table's way of writing."""

        def look(at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            key = at.astype(np.int64) << 32 | symbol
            place = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
            return self.keys[place] == key, self.to[place]

        found, to = look(state)
        anew, start = look(np.zeros_like(state))
        return np.where(found, to, ~np.where(anew, start, 0))


def _codes(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")


def letters_and_lower() -> tuple[np.ndarray, np.ndarray]:
    """For every code point, whether it is a letter, and its lower case where that is one letter."""
    letter, lower = np.zeros(0x110000, bool), np.arange(0x110000, dtype=np.uint32)
    for code in range(0x110000):
        c = chr(code)
        if unicodedata.category(c)[0] == "L":
            letter[code] = True
            small = c.lower()
            if small != c and len(small) == 1:
                lower[code] = ord(small)
    return letter, lower


class CrossParser:
    """All languages, parsed one after the other."""

    def __init__(self, samples: dict[str, str], segment: int = 256, width: int = 64) -> None:
        self.names, self.segment = sorted(samples), segment
        self.letter, self.lower = letters_and_lower()
        self.languages = [Language(samples[name], self.letter, self.lower, width) for name in self.names]

    def phrases(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(texts x languages) weighted phrases per character, characters, and whether a text has letters."""
        codes = [_codes(t) for t in texts]
        sizes = np.array([len(c) for c in codes], np.int64)
        rows = -(-sizes // self.segment)
        grid = np.zeros((int(rows.sum()), self.segment), np.uint32)
        pad = np.ones(grid.shape, bool)
        flat, real, at, letters = grid.ravel(), pad.ravel(), 0, np.zeros(len(texts), bool)
        for i, c in enumerate(codes):
            flat[at : at + len(c)] = c
            real[at : at + len(c)] = False
            letters[i] = bool(self.letter[c].any())
            at += int(rows[i]) * self.segment
        steps, pads = np.ascontiguousarray(grid.T), np.ascontiguousarray(pad.T)
        owner = np.repeat(np.arange(len(texts)), rows)
        out = np.zeros((len(texts), len(self.names)))
        for k, language in enumerate(self.languages):
            symbols, table = language.unfold(self.letter, self.lower)
            state, count, width = np.zeros(len(grid), np.int32), np.ones(len(grid), np.int32), language.width
            many = FIRST + len(language.letters) > width
            for step, gap in zip(steps, pads, strict=True):
                symbol = symbols[step]
                symbol[gap] = PAD
                if many and len(beyond := np.flatnonzero(symbol >= width)):
                    moved = language.rare(state[beyond], symbol[beyond])
                    symbol[beyond] = PAD
                    state = table[state * width + symbol]
                    state[beyond] = moved
                else:
                    state *= width
                    state += symbol
                    state = table[state]
                broke = state >> 31
                count -= broke
                state ^= broke
            out[:, k] = np.bincount(owner, count, len(texts)) * language.weight / np.maximum(sizes, 1)
        return out, sizes, letters

    def predict(self, texts: list[str]) -> tuple[list[str], list[float]]:
        cost, _, letters = self.phrases(texts)
        best = cost.argmin(axis=1)
        order = np.sort(cost, axis=1)
        score = 1 - order[:, 0] / np.maximum(order[:, 1], 1e-12) if order.shape[1] > 1 else np.ones(len(texts))
        names = [self.names[b] if ok else UNKNOWN for b, ok in zip(best, letters, strict=True)]
        return names, np.where(letters, np.clip(score, 0, 1), 0.0).tolist()


def in_fold(id_col: Column, folds: int, fold: int) -> Column:
    """Whether crc32(id as text) falls into a fold; false for a null id."""
    return F.coalesce(F.pmod(F.crc32(id_col.cast("string").cast("binary")), F.lit(folds)) == fold, F.lit(False))


def sample_texts(docs: DataFrame, *, id_col: str, text_col: str, lang_col: str, usable: Column, sample_rows: int, sample_chars: int, most_languages: int) -> dict[str, str]:
    """About ``sample_rows`` labelled texts of each language (never over twice as many, however often one id
    occurs), ``sample_chars`` characters of each language."""
    labelled = docs.where(usable & F.col(lang_col).isNotNull() & F.col(text_col).isNotNull())
    counts = labelled.groupBy(lang_col).agg(F.count("*").alias("n"))
    known = counts.limit(most_languages + 1).collect()
    if len(known) > most_languages:
        raise ValueError(f"more than {most_languages} different labels in {lang_col}")
    if not known:
        return {}
    draw = F.pmod(F.xxhash64(F.col(id_col), F.lit(5)), F.lit(1_000_000))
    below = F.least(F.lit(1.0), F.lit(float(sample_rows)) / F.col("n")) * 1_000_000 + 1
    share = max(400, 4 * sample_chars // sample_rows)
    shares = docs.sparkSession.createDataFrame([(r[0], r["n"]) for r in known], T.StructType([labelled.schema[lang_col], T.StructField("n", T.LongType())]))
    drawn = labelled.select(lang_col, draw.alias("d"), F.substring(text_col, 1, share).alias("t"))
    chosen = drawn.join(F.broadcast(shares), lang_col).where(F.col("d") < below).drop("n")
    place = F.row_number().over(Window.partitionBy(lang_col).orderBy("d", "t"))
    rows = chosen.withColumn("place", place).where(F.col("place") <= 2 * sample_rows).drop("place").collect()
    for lang in {r[0] for r in known} - {r[0] for r in rows}:  # a language whose few ids all draw high
        rows += drawn.where(F.col(lang_col) == lang).orderBy("d", "t").limit(sample_rows).collect()
    out: dict[str, str] = {}
    for lang, _, text in sorted(rows, key=lambda r: (r[0], r[1], r[2])):
        have = out.get(lang, "")
        if len(have) < sample_chars:
            out[lang] = (have + "\n" + text)[:sample_chars]
    return out


def identify(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", folds: int = 3, fold: int = 1, sample_rows: int = 64, sample_chars: int = 24_000, most_languages: int = 4096) -> DataFrame:
    """(id, held_out, lang_pred, score) for every row; learned from labelled rows outside the held-out fold."""
    usable = F.col(id_col).isNotNull() & ~in_fold(F.col(id_col), folds, fold)
    samples = sample_texts(docs, id_col=id_col, text_col=text_col, lang_col=lang_col, usable=usable, sample_rows=sample_rows, sample_chars=sample_chars, most_languages=most_languages)
    key = hash(tuple(sorted(samples.items())))
    shared = docs.sparkSession.sparkContext.broadcast(samples)
    source = docs.select(F.col(id_col), in_fold(F.col(id_col), folds, fold).alias("held_out"), F.col(text_col).alias("__text"))
    schema = T.StructType([docs.schema[id_col], *T._parse_datatype_string(RESULT).fields])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if key not in _BUILT:
            _BUILT.clear()
            _BUILT[key] = CrossParser(shared.value) if shared.value else None
        parser = _BUILT[key]
        for batch in batches:
            names, scores = [], []
            for part in in_parts(batch.column(2)):
                texts = [t or "" for t in part]
                n, s = parser.predict(texts) if parser else ([UNKNOWN] * len(texts), [0.0] * len(texts))
                names += n
                scores += s
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(names, pa.string()), pa.array(scores, pa.float64())], names=schema.names)

    return source.mapInArrow(run, schema)


def in_parts(column: pa.Array, chars: int = 6_000_000) -> Iterator[list[str | None]]:
    """A column's values in runs of about ``chars`` characters, whole values only."""
    part, size = [], 0
    for value in column:
        text = value.as_py()
        part.append(text)
        size += len(text or "")
        if size >= chars:
            yield part
            part, size = [], 0
    if part:
        yield part
