"""Removal of repeated passages: content-defined chunks of lines, built from DataFrame functions only.

A text is cut between lines where the content says so, hence at the same places wherever a passage is moved to:
before and after every line of at least ``long_words`` words, and in runs of shorter lines where a rolling hash
over the last two line hashes is divisible by ``modulus``.  Chunks of two or more lines, or of one long line, are
looked up globally by a 64-bit hash; of each group the first in order of (id, chunk number) is the original.  The
others are removed if their bytes equal the original's.

That rule finds few passages of short lines, since the cuts fall where they like and the chunks at both ends take
in neighbouring lines.  With ``passage_words`` every run of lines that is found twice and has so many words is
removed as well: from each line the shortest run of so many words that starts there, and to each line the one that
ends there, are looked up by 128 bits.  Together they cover any longer shared run from its first line with words to
its last.  Runs of long lines only are left to the chunks.  The original is the first in order of (id, line); a run
that overlaps its own original stays.  A line therefore only goes if an equal one stays at an earlier place.

Plan: the first scan cuts each text into lines once, counts words by spaces where these are plain, and writes the hashes
of chunks and runs, which alone are shuffled; partial aggregates absorb a passage that a third of all rows share.
Originals' bytes are cut from their documents, which a join by id finds, travel to their repetitions by a join that
adaptive execution can split, then to the documents by id, where bytes are compared within the row.  A text is cut once
in each of these steps.  No group is ever gathered.

Defined results: a null text stays null with no lines; the empty text has one empty line.  Rows of equal id are
versions of one document and get equal decisions; a null id is an id.  An empty table gives an empty one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vertexlog.llm.common import SPACES, let, materialise, once, same, words_of

#: Multiplier and modulus of the rolling hash; fixed values.
BASE, PRIME = 31, 2147483647


def line_hash(line: Column) -> Column:
    """Thirty-two bits of a line's MD5."""
    return F.conv(F.substring(F.md5(line.cast("binary")), 1, 8), 16, 10).cast("bigint")


def words_in(line: Column) -> Column:
    """Number of words of a line: from its spaces where single spaces are all its white space, else by cutting it."""
    other = line.startswith(" ") | line.endswith(" ")
    for run in ("  ", *SPACES[1:]):
        other = other | line.contains(run)
    spaces = F.octet_length(line) - F.octet_length(F.replace(line, F.lit(" "), F.lit("")))
    return F.when(line == "", 0).when(other, F.size(words_of(line))).otherwise(spaces + 1)


def counted_lines(text: Column) -> Column:
    """Array of (line, n): the lines of a text and their words."""
    return F.transform(F.split(text, "\n", -1), lambda x: F.struct(x.alias("line"), words_in(x).alias("n")))


def words_before(rows: Column, block: int = 128) -> Column:
    """For each counted line the words of all lines before it; summed in blocks, since an array that grows is copied each time."""
    last = lambda a: F.element_at(a, -1)
    zero = F.array(F.lit(0))
    blocks = F.transform(F.sequence(F.lit(0), F.floor((F.size(rows) - 1) / block).cast("int")), lambda b: F.slice(rows, b * block + 1, F.lit(block)))
    sums = F.transform(blocks, lambda part: F.aggregate(part, zero, lambda a, x: F.array_append(a, last(a) + x["n"])))

    def placed(sums: Column) -> Column:
        starts = F.aggregate(sums, zero, lambda a, part: F.array_append(a, last(a) + last(part)))
        return let(starts, lambda starts: F.flatten(F.transform(sums, lambda part, b: F.transform(F.slice(part, 1, F.size(part) - 1), lambda n: n + F.get(starts, b)))))

    return let(sums, placed)


def chunks_of(text: Column, long_words: int = 20, modulus: int = 4) -> Column:
    """Array of (no, lines, words, body): the content-defined chunks of a text, in order."""
    return F.when(text.isNotNull(), let(counted_lines(text), lambda rows: _chunks(rows, long_words, modulus)))


def _chunks(rows: Column, long_words: int, modulus: int) -> Column:
    def starts_here(i: Column) -> Column:
        hash_at = lambda k: F.coalesce(line_hash(F.try_element_at(rows, k)["line"]), F.lit(0))
        long_at = lambda k: F.coalesce(F.try_element_at(rows, k)["n"] >= long_words, F.lit(False))
        before = F.greatest(i - 1, F.lit(1))
        two = F.when(i > 2, hash_at(F.greatest(i - 2, F.lit(1)))).otherwise(0)
        rolling = (hash_at(before) * BASE + two) % PRIME
        return (i == 1) | long_at(i) | long_at(before) | (rolling % modulus == 0)

    def body(starts: Column, s: Column, k: Column) -> Column:
        end = F.coalesce(F.try_element_at(starts, k + 2), F.size(rows) + 1)
        part = F.slice(rows, s, end - s)
        return let(
            part,
            lambda p: F.struct(
                k.alias("no"),
                F.size(p).alias("lines"),
                F.aggregate(p, F.lit(0), lambda a, x: a + x["n"]).alias("words"),
                F.array_join(F.transform(p, lambda x: x["line"]), "\n").alias("body"),
            ),
        )

    numbers = F.sequence(F.lit(1), F.size(rows))
    return let(F.filter(numbers, starts_here), lambda starts: F.transform(starts, lambda s, k: body(starts, s, k)))


def repeated_chunks(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", long_words: int = 20, modulus: int = 4, broadcast_originals: int = 500_000, keys: DataFrame | None = None) -> DataFrame:
    """(id, __vl_again): for each id the chunks that repeat an earlier one, as array of (no, original body).

    Documents that hold originals are found by a broadcast of their ids, up to ``broadcast_originals`` of these (about
    a hundred bytes each), and by a join that shuffles all texts beyond; the result is the same.  ``keys`` are those of
    ``passage_keys``, if at hand.
    """
    keys = passage_keys(docs, id_col, text_col, long_words, modulus) if keys is None else keys
    keys = keys.where("chunk is not null").select("__vl_id", F.col("first").alias("no"), F.col("chunk").alias("h"))
    groups = keys.groupBy("h").agg(F.count("*").alias("n"), F.min(F.struct("__vl_id", "no")).alias("first")).where("n > 1")
    others = keys.join(groups.select("h", "first"), "h").where(~same(F.struct("__vl_id", "no"), F.col("first")))
    # the documents that hold originals are found by id first, so no other chunk's bytes travel
    origin = groups.groupBy(F.col("first.__vl_id").alias("__vl_id")).agg(F.collect_set(F.struct(F.col("first.no").alias("no"), F.col("h").alias("h"))).alias("__vl_first"))
    origin = materialise(origin, "originals")
    few = origin.limit(broadcast_originals + 1).count() <= broadcast_originals
    texts = docs.select(F.col(id_col).alias("id_"), F.col(text_col).alias("text_"))
    held = texts.join(F.broadcast(origin) if few else origin, same(F.col("id_"), F.col("__vl_id"))).select("__vl_first", F.explode(chunks_of(F.col("text_"), long_words, modulus)).alias("c"))
    named = held.withColumn("h", F.xxhash64("c.body")).where(F.array_contains("__vl_first", F.struct(F.col("c.no").alias("no"), F.col("h").alias("h"))))
    originals = named.groupBy("h").agg(F.min("c.body").alias("body"))
    again = others.select("__vl_id", "no", "h").join(originals, "h")
    return again.groupBy("__vl_id").agg(F.collect_set(F.struct("no", "body")).alias("__vl_again"))


def runs_of(text: Column, long_words: int = 20, passage_words: int = 50) -> Column:
    """Array of (first, last, h): the shortest runs of lines of so many words from and to each line, lines from 1."""
    return F.when(text.isNotNull(), let(counted_lines(text), lambda rows: _runs(rows, long_words, passage_words)))


def _runs(rows: Column, long_words: int, passage_words: int) -> Column:
    def runs(at: Column, before: Column) -> Column:
        line, far = lambda p: F.get(at, p), passage_words - 1
        pair = lambda first, last: F.when(first < last, F.struct(first.alias("first"), last.alias("last")))

        def around(x: Column, k: Column) -> Column:
            """The run from a line's first word on and the one up to its last word, this one unless it is its first line's own."""
            begin = F.get(before, k)
            first = line(begin + x["n"] - 1 - far)
            own = F.coalesce(line(F.get(before, first - 1) + far), F.lit(0))
            return F.when(x["n"] > 0, F.array(pair(k + 1, line(begin + far)), F.when(own != k + 1, pair(first, k + 1))))

        pairs = F.filter(F.flatten(F.filter(F.transform(rows, around), lambda w: w.isNotNull())), lambda w: w.isNotNull())
        return F.filter(F.transform(pairs, lambda w: hashed(F.slice(rows, w["first"], w["last"] - w["first"] + 1), w)), lambda w: w["h"].isNotNull())

    def hashed(part: Column, w: Column) -> Column:
        body = F.array_join(F.transform(part, lambda x: x["line"]), "\n")
        mixed = F.exists(part, lambda x: (x["n"] > 0) & (x["n"] < long_words))
        return F.struct(w["first"].alias("first"), w["last"].alias("last"), F.when(mixed, F.unhex(F.md5(body.cast("binary")))).alias("h"))

    # the line of each word, hence a run of words names its lines without a search
    owner = F.flatten(F.transform(rows, lambda x, k: F.array_repeat(k + 1, x["n"])))
    short = F.exists(rows, lambda x: (x["n"] > 0) & (x["n"] < long_words))
    return F.when(short, let(owner, lambda at: F.when(F.size(at) >= passage_words, let(words_before(rows), lambda before: runs(at, before)))))


def passage_keys(docs: DataFrame, id_col: str, text_col: str, long_words: int, modulus: int | None = None, passage_words: int | None = None) -> DataFrame:
    """(__vl_id, of, first, last, chunk, run): every chunk by its number and hash, every run by its lines and hash.

    Either kind is left out where its parameter is None; texts are cut into lines once for both.
    """
    text, none = F.col(text_col), F.array().cast("array<struct<first:int,last:int,chunk:bigint,run:binary>>")

    def keys(rows: Column) -> Column:
        wanted = lambda c: (c["words"] > 0) & ((c["lines"] > 1) | (c["words"] >= long_words))
        chunk = lambda c: F.struct(c["no"].alias("first"), F.lit(None).cast("int").alias("last"), F.xxhash64(c["body"]).alias("chunk"), F.lit(None).cast("binary").alias("run"))
        run = lambda r: F.struct(r["first"], r["last"], F.lit(None).cast("bigint").alias("chunk"), r["h"].alias("run"))
        chunks = none if modulus is None else F.transform(F.filter(_chunks(rows, long_words, modulus), wanted), chunk)
        runs = none if passage_words is None else F.coalesce(F.transform(_runs(rows, long_words, passage_words), run), none)
        return F.concat(chunks, runs)

    made = docs.select(F.col(id_col).alias("__vl_id"), F.xxhash64(text).alias("of"), F.explode(F.when(text.isNotNull(), let(counted_lines(text), keys))).alias("k"))
    return materialise(made.select("__vl_id", "of", "k.first", "k.last", "k.chunk", "k.run"), "passages")


def repeated_runs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", long_words: int = 20, passage_words: int = 50, keys: DataFrame | None = None) -> DataFrame:
    """(id, __vl_runs): for each id the runs of lines that repeat an earlier one, as array of (text hash, first, last)."""
    keys = passage_keys(docs, id_col, text_col, long_words, passage_words=passage_words) if keys is None else keys
    keys = keys.where("run is not null").select("__vl_id", "of", "first", "last", F.col("run").alias("h"))
    origin = F.min(F.struct("__vl_id", "first", "last")).alias("origin")
    groups = keys.groupBy("h").agg(F.count("*").alias("n"), origin).where("n > 1").select("h", "origin")
    apart = ~same(F.col("__vl_id"), F.col("origin.__vl_id")) | (F.col("first") > F.col("origin.last"))
    again = keys.join(groups, "h").where(apart)
    return again.groupBy("__vl_id").agg(F.collect_set(F.struct("of", "first", "last")).alias("__vl_runs"))


def _flagged(docs: DataFrame, id_col: str, text_col: str, long_words: int, modulus: int, passage_words: int | None) -> DataFrame:
    """docs with ``__vl_again`` and ``__vl_runs``, both null where nothing repeats."""
    keys = passage_keys(docs, id_col, text_col, long_words, modulus, passage_words)
    again = repeated_chunks(docs, id_col, text_col, long_words, modulus, keys=keys)
    joined = docs.join(again, same(docs[id_col], again["__vl_id"]), "left").drop("__vl_id")
    if passage_words is None:
        return joined.withColumn("__vl_runs", F.lit(None).cast("array<struct<of:bigint,first:int,last:int>>"))
    runs = repeated_runs(docs, id_col, text_col, long_words, passage_words, keys)
    joined = joined.join(runs, same(docs[id_col], runs["__vl_id"]), "left").drop("__vl_id")
    own = let(F.xxhash64(text_col), lambda h: F.filter("__vl_runs", lambda r: r["of"] == h))
    return joined.withColumn("__vl_runs", F.when(F.col("__vl_runs").isNotNull(), F.nullif(own, F.array().cast("array<struct<of:bigint,first:int,last:int>>"))))


def _chunk_flags(cut: Column) -> Column:
    """For each chunk whether it is removed: its number and its bytes equal those of an original."""
    gone = lambda c: F.array_contains(F.col("__vl_again"), F.struct(c["no"].alias("no"), c["body"].alias("body")))
    return F.when(F.col("__vl_again").isNull(), F.transform(cut, lambda c: F.lit(False))).otherwise(F.transform(cut, gone))


def _kept_lines(text: Column, cut: Column, gone: Column) -> Column:
    """Lines of a text that lie neither in a removed chunk nor in a removed run."""
    span = "array<struct<first:int,last:int>>"

    def step(a: Column, c: Column) -> Column:
        at = F.struct((a["at"] + 1).alias("first"), (a["at"] + c["lines"]).alias("last"))
        return F.struct((a["at"] + c["lines"]).alias("at"), F.when(c["gone"], F.array_append(a["out"], at)).otherwise(a["out"]).alias("out"))

    marked = F.zip_with(cut, gone, lambda c, g: F.struct(c["lines"].alias("lines"), g.alias("gone")))
    chunks = F.aggregate(marked, F.struct(F.lit(0).alias("at"), F.array().cast(span).alias("out")), step, lambda a: a["out"])
    runs = F.coalesce(F.transform("__vl_runs", lambda r: F.struct(r["first"].alias("first"), r["last"].alias("last"))), F.array().cast(span))

    def rest(lines: Column) -> Column:
        def walk(a: Column, w: Column) -> Column:
            between = F.slice(lines, a["at"], F.greatest(w["first"] - a["at"], F.lit(0)))
            return F.struct(F.greatest(a["at"], w["last"] + 1).alias("at"), F.when(w["first"] > a["at"], F.concat(a["out"], between)).otherwise(a["out"]).alias("out"))

        start = F.struct(F.lit(1).alias("at"), F.array().cast("array<string>").alias("out"))
        tail = lambda a: F.concat(a["out"], F.slice(lines, a["at"], F.greatest(F.size(lines) - a["at"] + 1, F.lit(0))))
        return F.aggregate(F.array_sort(F.concat(chunks, runs)), start, walk, tail)

    return let(F.split(text, "\n", -1), rest)


def _by_chunk(cut: Column, gone: Column) -> Column:
    return F.array_join(F.transform(F.filter(cut, lambda c, k: ~gone[k]), lambda c: c["body"]), "\n")


def _kept_text(text: Column, cut: Column, gone: Column) -> Column:
    return F.when(F.col("__vl_runs").isNull(), _by_chunk(cut, gone)).otherwise(F.array_join(_kept_lines(text, cut, gone), "\n"))


def deduplicate_lines(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", long_words: int = 20, modulus: int = 4, passage_words: int | None = 50) -> DataFrame:
    """One row per document: id, lines, chunks, removed chunks, lines and words, and the text that stays.

    Without ``passage_words`` the rule of chunks alone counts.
    """
    flagged = _flagged(docs.select(id_col, text_col), id_col, text_col, long_words, modulus, passage_words)
    by_run, source = F.col("__vl_runs").isNotNull(), F.col(text_col)
    words = lambda lines: F.aggregate(lines, F.lit(0), lambda a, x: a + words_in(x))

    def row(cut: Column, gone: Column) -> Column:
        lost = lambda field: F.aggregate(F.filter(cut, lambda c, k: gone[k]), F.lit(0), lambda a, c: a + c[field])
        total = lambda field: F.aggregate(cut, F.lit(0), lambda a, c: a + c[field])

        def result(lines: Column, words: Column, text: Column) -> Column:
            return F.struct(
                total("lines").cast("bigint").alias("n_lines"),
                F.size(cut).cast("bigint").alias("n_chunks"),
                F.size(F.filter(gone, lambda g: g)).cast("bigint").alias("removed_chunks"),
                lines.cast("bigint").alias("removed_lines"),
                words.cast("bigint").alias("removed_words"),
                text.alias("kept_text"),
            )

        by_lines = let(_kept_lines(source, cut, gone), lambda kept: result(total("lines") - F.size(kept), total("words") - words(kept), F.array_join(kept, "\n")))
        by_chunks = result(lost("lines"), lost("words"), _by_chunk(cut, gone))
        none = result(F.lit(0), F.lit(0), source)
        return F.when(by_run, by_lines).when(F.col("__vl_again").isNotNull(), by_chunks).otherwise(none)

    made = let(chunks_of(source, long_words, modulus), lambda cut: let(_chunk_flags(cut), lambda gone: row(cut, gone)))
    done = once(flagged, "r", F.when(source.isNotNull(), made))
    counts = ("n_lines", "n_chunks", "removed_chunks", "removed_lines", "removed_words")
    return done.select(id_col, *(F.coalesce(f"r.{c}", F.lit(0).cast("bigint")).alias(c) for c in counts), F.col("r.kept_text").alias("kept_text"))


def without_repeats(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", chars_col: str | None = "n_chars", long_words: int = 20, modulus: int = 4, passage_words: int | None = 50) -> DataFrame:
    """The documents with repeated chunks and runs cut out; those of which nothing but white space stays are dropped.

    Columns as in ``docs``; the character count follows the text where it changed.
    """
    flagged = _flagged(docs, id_col, text_col, long_words, modulus, passage_words)
    changed, source = F.col("__vl_again").isNotNull() | F.col("__vl_runs").isNotNull(), F.col(text_col)
    new = let(chunks_of(source, long_words, modulus), lambda cut: let(_chunk_flags(cut), lambda gone: _kept_text(source, cut, gone)))
    done = once(flagged, "__vl_text", F.when(changed, new).otherwise(source)).where(~changed | (F.btrim("__vl_text", F.lit(SPACES)) != ""))
    out = {text_col: F.col("__vl_text")}
    if chars_col in docs.columns:
        out[chars_col] = F.when(changed, F.length("__vl_text").cast(docs.schema[chars_col].dataType)).otherwise(F.col(chars_col))
    return done.select(*(out.get(c, F.col(c)).alias(c) for c in docs.columns))
