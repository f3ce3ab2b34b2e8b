"""Quality rules of documents and of their hosts, built from DataFrame functions only.

Every text is measured by itself (words, symbols, repeated lines, repeated three-word windows).  A host's
share of failing documents is then shrunk towards all hosts by a beta prior whose two parameters come from the
mean and variance of the hosts' failure rates, so a host of few documents is judged mostly by what hosts are
like.  Documents of a host whose shrunk rate exceeds ``max_rate`` are rejected with it.

Plan: measuring needs no shuffle and is done once, into a table (narrow, or with the texts that pass); hosts are a partial aggregate, so a host
that holds a third of all rows costs no more than others; verdicts come back by a broadcast join while hosts are
few (``broadcast_hosts``), else by a join that adaptive execution can split.

Defined results: null text has no words, hence fails; documents without a host form a host of their own; one host
or equal rates give the prior of ``prior_weight`` documents at the mean rate; an empty table gives an empty one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vertexlog.llm.common import let, materialise, once, same, words_of

SYMBOLS = "#*$%&|<>"
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def repeated_words(words: Column, few: int = 48) -> Column:
    """Words inside three-word windows that the text has twice or more.

    Texts whose window hashes all differ are done at once; else the hashes are sorted to find the repeated ones.  At most
    ``few`` different ones are looked up directly; beyond that, (hash, place) pairs are sorted, so the time stays n log n.
    """

    def covered(places: Column) -> Column:
        step = lambda a, p: F.struct((a["n"] + F.least(p - a["last"], F.lit(3))).alias("n"), p.alias("last"))
        return F.aggregate(places, F.struct(F.lit(0).alias("n"), F.lit(-3).alias("last")), step, lambda a: a["n"])

    def by_lookup(hashes: Column, twice: Column) -> Column:
        hit = F.transform(hashes, lambda h, i: F.when(F.array_contains(twice, h), i))
        return F.array_compact(hit)

    def by_sorting(hashes: Column) -> Column:
        pairs = F.sort_array(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

        def twins(p: Column) -> Column:
            at = lambda k: F.try_element_at(p, k)["h"]
            twin = lambda x, k: (F.coalesce(at(k + 2) == x["h"], F.lit(False))) | (F.when(k > 0, at(F.greatest(k, F.lit(1))) == x["h"]).otherwise(False))
            return F.sort_array(F.transform(F.filter(p, twin), lambda x: x["i"]))

        return let(pairs, twins)

    def twice_of(hashes: Column) -> Column:
        return let(F.sort_array(hashes), lambda s: F.array_distinct(F.filter(F.slice(s, 2, F.greatest(F.size(s) - 1, F.lit(0))), lambda x, i: x == s[i])))

    def count(hashes: Column) -> Column:
        return let(
            twice_of(hashes),
            lambda twice: F.when(F.size(twice) == 0, 0).when(F.size(twice) <= few, covered(by_lookup(hashes, twice))).otherwise(covered(by_sorting(hashes))),
        )

    windows = F.transform(F.slice(words, 1, F.greatest(F.size(words) - 2, F.lit(0))), lambda w, i: F.xxhash64(w, words[i + 1], words[i + 2]))
    unless_all_differ = lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), 0).otherwise(count(h))
    return F.when(F.size(words) < 4, 0).otherwise(let(windows, unless_all_differ))


def measures(text: Column) -> Column:
    """Struct of the five measures of a text."""
    full = F.coalesce(text, F.lit(""))

    def all_of(words: Column) -> Column:
        lines = F.filter(F.split(full, "\n", -1), lambda x: x.rlike("[^\\x20\\x09-\\x0D]"))
        return F.struct(
            F.size(words).cast("bigint").alias("n_words"),
            F.aggregate(words, F.lit(0), lambda n, w: n + F.length(w)).cast("bigint").alias("word_chars"),
            F.length(F.regexp_replace(full, "[^#*$%&|<>]+", "")).cast("bigint").alias("n_symbols"),
            let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("bigint").alias("n_dup_lines"),
            repeated_words(words).cast("bigint").alias("n_repeat_words"),
        )

    return let(words_of(text), all_of)


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def host_verdicts(failures: DataFrame, prior_weight: float = 20.0, max_rate: float = 0.6) -> DataFrame:
    """(host, failed) rows -> per host: n, failures, shrunk rate, and whether it is rejected."""
    hosts = failures.groupBy("host").agg(F.count("*").alias("n"), F.sum(F.col("failed").cast("bigint")).alias("k"))
    rate = F.col("k") / F.col("n")
    prior = hosts.agg(F.avg(rate).alias("m"), F.coalesce(F.var_samp(rate), F.lit(0.0)).alias("v"))
    weight = F.when((F.col("v") > 0) & (F.col("m") * (1 - F.col("m")) > F.col("v")), F.col("m") * (1 - F.col("m")) / F.col("v") - 1).otherwise(F.lit(prior_weight))
    prior = prior.select("m", weight.alias("w"))  # one row
    shrunk = (F.col("k") + F.col("m") * F.col("w")) / (F.col("n") + F.col("w"))
    return hosts.join(F.broadcast(prior)).select("host", "n", "k", shrunk.alias("host_rate"), (shrunk > max_rate).alias("host_rejected"))


def _bad_hosts(measured: DataFrame, host: str, prior_weight: float, max_rate: float, broadcast_hosts: int) -> DataFrame:
    verdicts = materialise(host_verdicts(measured.select(F.col(host).alias("host"), F.col("base_failed").alias("failed")), prior_weight, max_rate), "hosts")
    return F.broadcast(verdicts) if verdicts.count() <= broadcast_hosts else verdicts


def judge(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", prior_weight: float = 20.0, max_rate: float = 0.6, broadcast_hosts: int = 10_000) -> DataFrame:
    """One row per document: id, measures, ``base_failed``, ``host_rate`` and ``kept``."""
    measured = docs.select(F.col(id_col).alias("__id"), F.col(host_col).alias("__host"), measures(F.col(text_col)).alias("m"))
    table = materialise(measured.select("__id", "__host", "m.*").withColumn("base_failed", base_failed()), "measures")
    hosts = _bad_hosts(table, "__host", prior_weight, max_rate, broadcast_hosts)
    joined = table.join(hosts, same(table["__host"], hosts["host"]), "left")
    kept = ~F.col("base_failed") & ~F.coalesce("host_rejected", F.lit(False))
    return joined.select(F.col("__id").alias(id_col), *MEASURES, "base_failed", kept.alias("kept"), F.round("host_rate", 9).alias("host_rate"))


def keep_good(docs: DataFrame, *, text_col: str = "text", host_col: str = "source", prior_weight: float = 20.0, max_rate: float = 0.6, broadcast_hosts: int = 10_000) -> DataFrame:
    """The documents that pass their own rules and whose host passes; columns unchanged."""
    measured = once(docs, "__vl_m", measures(F.col(text_col)))
    failed = (F.col("__vl_m.n_words") < 50) | (100 * F.col("__vl_m.n_repeat_words") > 50 * F.col("__vl_m.n_words"))
    # texts are measured once; those that fail by themselves leave their host and verdict only
    columns = [F.when(~F.col("__vl_failed"), F.col(c)).alias(c) if c == text_col else F.col(c) for c in docs.columns]
    table = materialise(once(measured, "__vl_failed", failed).select(*columns, "__vl_failed"), "judged")
    hosts = _bad_hosts(table.select(F.col(host_col).alias("__host"), F.col("__vl_failed").alias("base_failed")), "__host", prior_weight, max_rate, broadcast_hosts)
    bad = hosts.where("host_rejected").select(F.col("host").alias("__vl_bad"))
    passed = table.where("not __vl_failed")
    return passed.join(bad, same(passed[host_col], F.col("__vl_bad")), "left_anti").select(docs.columns)
