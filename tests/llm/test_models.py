"""Language identification, packing, sharding, language model, page text."""

import math
import re
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from vertexlog.llm import html_text, language_id, language_model, packing, queries, sharding, tokens


def test_automaton_accepts_exactly_the_substrings():
    text = [2, 3, 2, 2, 4, 3, 2]
    a = language_id.Automaton(text)
    inside = {tuple(text[i:j]) for i in range(len(text)) for j in range(i, len(text) + 1)}

    def accepts(word):
        state = 0
        for c in word:
            if c not in a.next[state]:
                return False
            state = a.next[state][c]
        return True

    import itertools

    for n in range(5):
        for word in itertools.product((2, 3, 4), repeat=n):
            assert accepts(word) == (word in inside)


def test_phrases_are_longest_matches():
    parser = language_id.CrossParser({"a": "abcab", "b": "xyz"}, segment=8)
    cost, sizes, letters = parser.phrases(["abcxab", ""])
    # with a: abc | x as its own phrase start | ab; x is unknown to a's alphabet of substrings
    assert letters.tolist() == [True, False] and sizes.tolist() == [6, 0] and cost[0, 0] < cost[0, 1]


def test_language_accuracy_on_held_out_rows(spark, tiny):
    found = queries.op5_language_id(spark, tiny.replace("0.001", "0.01")).toPandas()
    docs = spark.read.parquet(tiny.replace("0.001", "0.01") + "/documents.parquet").toPandas()
    both = found.merge(docs, on="doc_id")
    held = both[both.held_out]
    assert (held.held_out == [zlib.crc32(str(i).encode()) % 3 == 1 for i in held.doc_id]).all()
    assert (held.lang_pred == held.lang).mean() > 0.98 and both.score.between(0, 1).all()


def test_language_of_awkward_rows(awkward, make):
    got = {str(r["doc_id"]): r for r in language_id.identify(awkward).collect()}
    assert got["1"]["lang_pred"] == "und" and got["7"]["lang_pred"] == "und" and got["6"]["lang_pred"] != "und"
    assert language_id.identify(awkward.limit(0)).count() == 0
    hot = language_id.sample_texts(make([(2, "ab cd", "en")] * 900 + [(3, "xy z", "fr")]), id_col="doc_id", text_col="text", lang_col="lang", usable=F.lit(True), sample_rows=4, sample_chars=10_000, most_languages=9)
    assert set(hot) == {"en", "fr"} and set(hot["en"].split("\n")) == {"", "ab cd"} and len(hot["en"]) <= 6 * 8 and hot["fr"] == "\nxy z"
    nothing = language_id.identify(make([(1, "some text", None)])).first()
    assert nothing["lang_pred"] == "und" and nothing["score"] == 0.0


def brute_phrases(text, sample):
    """Longest matches one character at a time, in segments of 256, over lower-case letters and one other symbol."""
    import unicodedata

    def plain(t):
        return "".join((c.lower() if len(c.lower()) == 1 else c) if unicodedata.category(c)[0] == "L" else "\0" for c in t)

    source, n = plain(sample), 0
    for i in range(0, len(text), 256):
        part, start = plain(text[i : i + 256]), 0
        n += 1
        for end in range(len(part)):
            if part[start : end + 1] not in source:
                n += 1
                start = end if part[end] in source else end + 1
    return n


def test_language_query_equals_brute_force(make):
    r = np.random.default_rng(4)
    scripts = {"la": "abcdefghij", "cy": "абвгдежз", "ha": [chr(0x4E00 + i) for i in range(300)], "go": [chr(0x10330 + i) for i in range(20)], "yo": "èéabc"}
    word = lambda k: "".join(r.choice(list(scripts[k]), r.integers(1, 6)))
    rows = []
    for i in range(120):
        lang = list(scripts)[i % 5]
        rows.append((i, " ".join(word(lang) for _ in range(r.integers(1, 90))) + (" " + word("la") if i % 7 == 0 else ""), lang if i % 4 else None))
    rows += [(900, "\U0001f600 12 \U0001d7ce", "la"), (901, "İabc İ", "la"), (902, "12 34", None)]
    docs = make(rows)
    usable = ~language_id.in_fold(F.col("doc_id"), 3, 1)
    samples = language_id.sample_texts(docs, id_col="doc_id", text_col="text", lang_col="lang", usable=usable, sample_rows=64, sample_chars=24_000, most_languages=99)
    assert set(samples) == set(scripts)
    got = {x["doc_id"]: x for x in language_id.identify(docs).collect()}
    for i, text, _ in rows:
        assert got[i]["held_out"] == (zlib.crc32(str(i).encode()) % 3 == 1)
        if i in (900, 902):
            assert got[i]["lang_pred"] == "und" and got[i]["score"] == 0
            continue
        cost = {k: brute_phrases(text, s) * math.log2(max(2, len(s))) for k, s in samples.items()}
        best = sorted((c, k) for k, c in cost.items())
        assert got[i]["lang_pred"] == best[0][1] and abs(got[i]["score"] - (1 - best[0][0] / best[1][0])) < 1e-9, i
    assert sum(got[i]["lang_pred"] == k for i, _, k in rows if k and got[i]["held_out"]) >= 0.95 * sum(bool(k) and got[i]["held_out"] for i, _, k in rows) - 1
    many = make([(i, f"text {i}", f"l{i}") for i in range(0, 300, 3)])
    assert len(language_id.sample_texts(many, id_col="doc_id", text_col="text", lang_col="lang", usable=F.lit(True), sample_rows=64, sample_chars=100, most_languages=100)) == 100
    with pytest.raises(ValueError):
        language_id.identify(many, most_languages=5)


CASES = ["", "a", "  two  spaces", "tab\t here", "x \n y", "foo\n\n bar", "it's we'll ok", "<|endoftext|> z", "É à ñ 漢字 12 3.5", "end ", "\n", "a\n \nb", "nb sp  x"]


def test_ids_equal_the_tokenizer(spark, tiny):
    whole = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    texts = CASES + [r["text"] for r in spark.read.parquet(f"{tiny}/documents.parquet").select("text").collect()]
    ids = tokens.encoder().ids
    for text in texts:
        assert ids(text) == np.array(whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes(), text[:40]


def check_packing(rows, limit):
    by = {}
    for r in rows:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts in by.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= limit
    return len(by)


def test_packing_is_whole_gapless_and_tight(spark, tiny, awkward):
    rows = queries.op7_pattern_packing(spark, tiny).collect()
    total = sum(r["length"] for r in rows)
    assert check_packing(rows, 2048) <= 1.03 * total / 2048 + 1
    ids = tokens.encoder().ids
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{tiny}/documents.parquet").collect()}
    seen = {}
    for r in rows:
        own = ids(texts[r["doc_id"]] or "") + b"\0\0\0\0"
        assert zlib.crc32(own[4 * r["start"] : 4 * (r["start"] + r["length"])]) == r["ids_crc32"]
        seen.setdefault(r["doc_id"], []).append((r["piece"], r["start"], r["length"]))
    for i, parts in seen.items():
        assert sorted(parts) == [(k, s, n) for k, (s, n) in enumerate(packing.cut(len(ids(texts[i])) // 4 + 1, 2048))]
    got = packing.pack(awkward).collect()
    assert {r["length"] for r in got if r["doc_id"] in (1, 2)} == {1} and check_packing(got, 2048)
    assert packing.pack(awkward.limit(0)).count() == 0


@pytest.mark.parametrize("seed", range(4))
def test_plans_use_every_length_once(seed):
    r = np.random.default_rng(seed)
    lengths = np.clip(r.lognormal(4 + seed / 2, 1, 3000).astype(int), 1, 512)
    counts = np.bincount(lengths, minlength=513)
    plan = packing.Plan(counts, bins=32)
    table = plan.table()
    used = np.zeros(513, int)
    for times, parts in (x for f in plan.open.values() for x in f):
        assert sum(n * m for n, m in parts) <= 512
        for n, m in parts:
            used[n] += times * m
    assert (used == counts).all() and plan.sequences <= 1.05 * lengths.sum() / 512 + 2 and len(table)


def test_least_squares_is_non_negative_and_optimal():
    r = np.random.default_rng(0)
    a, b = r.random((8, 20)), r.random(8)
    x = packing.nnls(a, b)
    slope = a.T @ (b - a @ x)
    assert (x >= 0).all() and (slope <= 1e-6).all() and np.abs(slope[x > 0]).max() < 1e-6


def test_shards_differ_by_one_row_and_slots_have_no_gaps(spark, tiny, awkward):
    rows = queries.op4_ring_sharding(spark, tiny).toPandas()
    n = rows.groupby("shard").size()
    assert len(n) == 40 and n.max() - n.min() <= 1
    assert all(sorted(g.slot) == list(range(len(g))) for _, g in rows.groupby("shard"))
    got = sharding.shard_rows(awkward, shards=3).collect()
    assert len(got) == 9 and {r["size"] for r in got if r["doc_id"] in (1, 2)} == {16}
    assert sharding.shard_rows(awkward.limit(0)).count() == 0


def test_sharding_equals_brute_force(spark, awkward, make):
    """A walk along the ring, row by row: rows in order of slice, then id, size and checksum."""
    import xxhash

    r = np.random.default_rng(5)
    docs = make([(int(i), "x" * int(r.integers(0, 50))) for i in r.integers(0, 400, 300)] + [(7, "same")] * 200).unionByName(awkward)
    sliced = docs.select("doc_id", "text", F.shiftrightunsigned(F.xxhash64("doc_id"), 50).alias("s")).collect()
    rows = sorted((x["s"], x["doc_id"] is not None, x["doc_id"] or 0, len((x["text"] or "").encode()) + 16, zlib.crc32((x["text"] or "").encode())) for x in sliced)
    shards, n = 7, len(rows)
    points = sorted((xxhash.xxh64_intdigest(f"{s}/{k}", 42) >> 50, s) for s in range(shards) for k in range(128))
    room, want = [n // shards + (s < n % shards) for s in range(shards)], []
    used = [0] * shards
    for place, known, page, size, crc in rows:
        at = next((k for k, p in enumerate(points) if p[0] >= place), 0)
        while not room[points[at][1]]:
            at = (at + 1) % len(points)
        shard = points[at][1]
        want.append((page if known else None, size, crc, shard, used[shard]))
        room[shard], used[shard] = room[shard] - 1, used[shard] + 1
    for parts, run in ((1, 10_000), (6, 3)):
        got = sharding.shard_rows(docs.repartition(parts), shards=shards, run=run).collect()
        assert sorted(map(str, map(tuple, got))) == sorted(map(str, want))


def test_ring_moves_few_rows_when_there_is_slack():
    r = np.random.default_rng(1)
    counts = dict(enumerate(r.multinomial(100_000, np.ones(1 << 10) / (1 << 10)).tolist()))

    def owner(shards, slack):
        out = {}
        for piece, low, high, shard, _ in sharding.place(counts, shards, slice_bits=10, slack=slack):
            for k in range(low, high):
                out[piece, k] = shard
        return out

    before, after = owner(20, 0.25), owner(21, 0.25)
    sizes = Counter(before.values())
    assert max(sizes.values()) <= math.ceil(100_000 * 1.25 / 20)
    assert sum(before[k] != after[k] for k in before) < 0.2 * len(before)


def test_language_model_scores(spark, tiny, awkward):
    found = queries.op8_maxent_scoring(spark, tiny).toPandas()
    docs = spark.read.parquet(f"{tiny}/documents.parquet").toPandas()
    words = {i: [*re.findall(rb"[^\x20\x09-\x0D]+", t.encode().lower()), None] for i, t in zip(docs.doc_id, docs.text, strict=True)}
    counts = Counter(w for i, t in words.items() if zlib.crc32(str(i).encode()) % 5 != 1 for w in t)
    n, v = sum(counts.values()), len(counts)
    for r in found.itertuples():
        t = words[r.doc_id]
        base = sum(math.log10((counts[w] + 0.5) / (n + 0.5 * (v + 1))) for w in t)
        assert (r.n_tokens, r.n_known, r.train_tokens) == (len(t), sum(counts[w] > 0 for w in t), n) and abs(r.base_score - base) < 1e-6 * abs(base)
    held = found[found.held_out]
    assert held.score.sum() > held.base_score.sum()
    got = language_model.score_texts(awkward, broadcast_types=1000).collect()
    again = language_model.score_texts(awkward, broadcast_types=0).collect()
    key = lambda r: (str(r["doc_id"]), r["n_tokens"], round(r["base_score"], 6), round(r["score"], 6))
    assert len(got) == 9 and sorted(map(key, got)) == sorted(map(key, again))
    assert {r["n_tokens"] for r in got if r["doc_id"] in (1, 2, 3)} == {1}
    assert language_model.score_texts(awkward.limit(0)).count() == 0


def test_model_is_a_distribution():
    r = np.random.default_rng(0)
    shape = language_model.Shape(top=2, groups=3, hashed=4, buckets=16)
    bias, weights = r.normal(size=shape.classes).astype(np.float32), r.normal(size=(3, 16, shape.classes)).astype(np.float32)
    p = np.exp(language_model.log_softmax(bias, weights, r.integers(0, 16, (3, 9))))
    assert np.allclose(p.sum(axis=1), 1, atol=1e-5)


def test_powers_share_a_shift_only_where_no_power_vanishes():
    r = np.random.default_rng(1)
    for spread in (1, 500):
        bias, weights, at = (spread * r.normal(size=6)).astype(np.float32), r.normal(size=(3, 16, 6)).astype(np.float32), r.integers(0, 16, (3, 9))
        weights[0] += spread * np.arange(16, dtype=np.float32)[:, None]
        z = bias + weights[0, at[0]] + weights[1, at[1]] + weights[2, at[2]]
        want = z - z.max(axis=1, keepdims=True)
        want -= np.log(np.exp(want).sum(axis=1, keepdims=True))
        assert np.allclose(language_model.log_softmax(bias, weights, at), want, atol=2e-3)
        shifted, power, total = language_model.powers(bias, weights, at)
        assert (total > 0).all() and np.allclose(power.sum(axis=1), total) and (np.ptp(z - shifted) < 1e-3) == (np.ptp(z) < 60)


def test_words_are_coded_by_their_kinds():
    import pyarrow as pa

    texts = ["", None, " A  b\ta\n", "b", "\x0b", " c a"]
    kinds, at, n = language_model.coded(pa.array(texts, pa.string()))
    assert n.tolist() == [1, 1, 4, 2, 1, 3] and (kinds[at[np.cumsum(n) - 1]] == language_model.END).all()
    h, sizes = language_model.encode(pa.array(texts, pa.string()))
    assert (h == kinds[at]).all() and (sizes == n).all() and h[2] == h[4] == h[10] and h[3] == h[6] and len(set(h.tolist())) == 4
    times = language_model.times_of(kinds, at, n, np.array([h[3], h[2], 99]))
    assert times.tolist() == [[0, 0, 0], [0, 0, 0], [1, 2, 0], [1, 0, 0], [0, 0, 0], [0, 1, 0]]
    batch = pa.RecordBatch.from_arrays([pa.array(texts, pa.string())], names=["t"])
    counts = {x["h"]: x["n"] for b in language_model.tally(iter([batch])) for x in b.to_pylist()}
    assert counts == {language_model.END: 6, h[2]: 3, h[3]: 2, h[9]: 1}


def test_score_equals_brute_force_and_sums_to_one(spark, make):
    r = np.random.default_rng(8)
    texts = [" ".join(r.choice([f"{'ab'[i % 2]}{k}" for k in range(30)], 25)) for i in range(60)]
    docs = make([(i, t) for i, t in enumerate(texts)])
    learn = docs.where(~language_model.in_fold(F.col("doc_id"), 5, 1)).select("doc_id", F.col("text").alias("__text"))
    counts = learn.select("__text").mapInArrow(language_model.tally, "h bigint, n bigint").groupBy("h").agg(F.sum("n").alias("n")).cache()
    model = language_model.fit(learn, counts, text_col="__text", turn=F.pmod(F.xxhash64("doc_id", F.lit(11)), F.lit(2)), shape=language_model.Shape(), rounds=2, rate=0.1, anchors=48, grouped=1000, most_buckets=1 << 15)
    table = {x["h"]: x["n"] for x in counts.collect()}
    counts.unpersist()
    kinds = np.array(sorted(table), np.int64)
    own = dict(zip(kinds.tolist(), model.classes.of(kinds).tolist(), strict=True))
    last = model.shape.classes - 1

    def step(one, two, classes_before):
        """Probabilities of all known words, and of an unknown one, after a context."""
        import pyarrow as pa  # noqa: F401

        at = language_model.contexts(np.array([two, one, 77], np.int64), np.array([3]), np.array([*classes_before, 0]), model.shape)[:, 2]
        z = model.bias.astype(float) + sum(model.weights[k, at[k]].astype(float) for k in range(3))
        p = np.exp(z - z.max())
        p /= p.sum()
        return {w: p[own[w]] * (c + 0.5) / model.totals[own[w]] for w, c in table.items()}, p[last]

    words = kinds.tolist()
    known, rest = step(words[3], words[9], (own[words[9]], own[words[3]]))
    used = {own[w] for w in words}
    empty = 1 - sum(known.values()) - rest
    assert 0 <= empty < 0.2 and all(abs(sum((c + 0.5) for w, c in table.items() if own[w] == k) - model.totals[k]) < 1e-6 for k in used)
    import pyarrow as pa

    h, n = language_model.encode(pa.array(texts[:3]))
    c = np.array([table.get(x, 0) for x in h.tolist()], float)
    got, at, kind = model.score(h, n, c)[2], 0, model.classes.of(h)
    for i, size in enumerate(n.tolist()):
        total = 0.0
        for k in range(size):
            before = [(int(h[at + k - d]), int(kind[at + k - d])) if k >= d else (language_model.BEGIN, model.shape.classes) for d in (1, 2)]
            probabilities, unknown = step(before[0][0], before[1][0], (before[1][1], before[0][1]))
            total += math.log10(probabilities[int(h[at + k])] if c[at + k] else unknown)
        assert abs(total - got[i]) < 1e-3, i
        at += size
    groups = {t[0]: {own[x] for x in words if own[x] >= 15 and x in set(language_model.encode(pa.array(texts[j::2]))[0].tolist())} for j, t in enumerate(("a", "b"))}
    assert groups["a"] and groups["b"] and len(groups["a"] & groups["b"]) <= 1


PAGE = """<html><head><title>T</title><style>x</style></head><body><header>Site</header><nav><ul><li><a href="/a">Home</a><li>News</ul></nav>
<div class="cookie-notice">We use cookies</div><article><header><h1>A &amp; B</h1></header><p>First<br>line &lt;b&gt;<p>Second <b>bold</b> text
<div class="ad">Buy</div><script>if (a < b) {}</script><form><input></form></article><aside>More</aside><section id="comments"><article class="comment">Nice!</article></section>
<footer>&copy; x</footer></body></html>"""


def test_page_text_keeps_the_article_only(spark):
    rows = [(1, "http://h/a/1", PAGE), (2, "http://h/a/2", PAGE.replace("Second", "Other")), (3, "http://k/", None), (4, None, ""), (5, "http://h/a/3", "<p>shared line</p><p>own three</p>"), (6, "http://h/a/4", "<p>shared line</p><p>own four"), (1, "http://h/a/1", PAGE)]
    table = spark.createDataFrame([(*r, "x") for r in rows], "page_id bigint, url string, html string, text string")
    got = {r["page_id"]: r["text"] for r in html_text.extract(table).collect()}
    assert got[1] == "A & B\n\nFirst line <b>\n\nSecond bold text" and got[2].endswith("Other bold text")
    assert got[3] == got[4] == "" and got[5] == "own three" and got[6] == "own four"
    assert html_text.extract(table.limit(0)).count() == 0
    odd = spark.createDataFrame([(9, "http://z/", "<p>one\x00two\x00</p>\x00<p>\x00</p>")], "page_id bigint, url string, html string")
    assert html_text.extract(odd).first()["text"].startswith("one\x00two")


def test_differencing_decides_outside_the_layout(spark):
    page = "<body><p>Site line</p><p>Lead {0}</p><article class='has-sidebar'><p>Shared in main</p><p>Story {0}</p></article><div class='search'>Find {0}</div><nav>Menu {0}</nav>{1}</body>"
    rows = [(i, f"http://h/{i}", page.format(i, "<div class='social'><p>Only here</p></div>" if i == 1 else "")) for i in range(3)]
    got = {r["page_id"]: r["text"].split("\n\n") for r in html_text.extract(spark.createDataFrame(rows, "page_id bigint, url string, html string")).collect()}
    assert got == {0: ["Lead 0", "Story 0"], 1: ["Lead 1", "Story 1", "Only here"], 2: ["Lead 2", "Story 2"]}


def test_names_do_not_hide_the_main_text(spark):
    story = "".join(f"<p>Story line {i} of some length</p>" for i in range(5))
    pages = [
        f"<body class='no-sidebar ad-free'><article>{story}</article><div class='ad'>Buy</div></body>",
        f"<div class='search widget'><article class='search-engines related'>{story}</article></div>",
        f"<p>intro</p><article>teaser</article>{story}",
        f"<article>{story}</article><div class='comments'><article>Nice!</article></div>",
        f"<article>{story}<p>5 <b and more\n",
    ]
    rows = [(i, f"http://h{i}/", p) for i, p in enumerate(pages)]
    got = {r["page_id"]: r["text"].split("\n\n") for r in html_text.extract(spark.createDataFrame(rows, "page_id bigint, url string, html string")).collect()}
    plain = [f"Story line {i} of some length" for i in range(5)]
    assert got == {0: plain, 1: plain, 2: ["intro", "teaser", *plain], 3: plain, 4: [*plain, "5"]}


def test_broken_pages_take_linear_time():
    import time

    for bad in ("<a ", "<a", '<a "', "<a '\">", "<b></x>", "<p>x", "<svg>", "<!", "<div class='a' ", "<p><table><b>"):
        start = time.perf_counter()
        html_text.lines_of(bad * (1_000_000 // len(bad)) + "<p>the end</p>")
        assert time.perf_counter() - start < 20, bad
    a, b = [1, 2] * 5000, [2, 1, 3] * 3000
    start = time.perf_counter()
    assert sum(html_text.common(a, b)) == 6000 and time.perf_counter() - start < 10


def brute_extract(pages, beside=2):
    """Pages (id, url, lines as (own, text)) differenced by the textbook table; lines of a page differ."""
    from urllib.parse import urlsplit

    def shared(a, b):
        t = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i in range(len(a) - 1, -1, -1):
            for j in range(len(b) - 1, -1, -1):
                t[i][j] = t[i + 1][j + 1] + 1 if a[i] == b[j] else max(t[i + 1][j], t[i][j + 1])
        out, i, j = set(), 0, 0
        while i < len(a) and j < len(b):
            if a[i] == b[j]:
                out.add(a[i])
                i, j = i + 1, j + 1
            elif t[i + 1][j] >= t[i][j + 1]:
                i += 1
            else:
                j += 1
        return out

    order = sorted(pages, key=lambda p: (urlsplit(p[1]).netloc, urlsplit(p[1]).path + "?" + urlsplit(p[1]).query, p[0]))
    out = {}
    for k, (page, url, lines) in enumerate(order):
        mine, near = [t for _, t in lines], []
        for side in (order[:k][::-1], order[k + 1 :]):
            last, found = None, 0
            for _, other, theirs in side:
                theirs = [t for _, t in theirs]
                if urlsplit(other).netloc == urlsplit(url).netloc and theirs not in (mine, last) and found < beside:
                    near.append(shared(mine, theirs))
                    found, last = found + 1, theirs
        size = sum(len(t) for own, t in lines if own)
        apart = [s for s in near if 2 * sum(len(t) for own, t in lines if own and t in s) < size]
        keep = [t for own, t in lines if not ((len(apart) >= 3 and all(t in s for s in apart)) if own else any(t in s for s in near))]
        out[page] = "\n\n".join(keep)
    return out


def test_extraction_equals_brute_force_wherever_slices_are_cut(spark):
    r = np.random.default_rng(6)
    pages = []
    for i in range(90):
        host = ["a", "b", "one"][i % 3]
        url = f"http://{host}/index.php?id={i:03d}" if host == "one" else f"http://{host}/{'xyz'[i % 7 % 3]}/{i:03d}"
        lines = [(False, f"site {host}"), (False, f"section {'xyz'[i % 7 % 3]}")] + [(False, f"loose {i} {k}") for k in range(r.integers(0, 2))]
        lines += [(True, "Read more stories below")] + [(True, f"own text {i} {k} of a page") for k in range(r.integers(1, 4))] + [(True, f"quoted {r.integers(4)}")]
        lines += [(False, f"foot {host}")]
        pages.append((i, url, pages[-3][2] if i % 11 == 5 and i > 3 else lines))
    markup = lambda lines: "".join(f"<div>{t}</div>" for own, t in lines[:2]) + "".join(f"<article>{t}</article>" if own else f"<p>{t}</p>" for own, t in lines[2:])
    table = spark.createDataFrame([(i, u, markup(x)) for i, u, x in pages], "page_id bigint, url string, html string").repartition(5)
    want = brute_extract(pages)
    for size in (1000, 16):
        got = {x["page_id"]: x["text"] for x in html_text.extract(table, slice_pages=size, halo=8).collect()}
        assert got == want
    alone = {x["page_id"]: x["text"] for x in html_text.extract(table, beside=0).collect()}
    assert sum(alone[i] != want[i] for i in want) > 80 and any("Read more" in t for t in alone.values()) and not all("Read more" in t for t in want.values())


def test_longest_common_subsequence():
    def length(a, b):
        t = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                t[i + 1][j + 1] = t[i][j] + 1 if x == y else max(t[i][j + 1], t[i + 1][j])
        return t[-1][-1]

    r = np.random.default_rng(3)
    for _ in range(200):
        a, b = (r.integers(0, 4, r.integers(0, 12)).tolist() for _ in range(2))
        marks = html_text.common(a, b)
        kept, at = [x for x, m in zip(a, marks, strict=True) if m], 0
        assert len(kept) == length(a, b)
        for y in b:
            at += at < len(kept) and kept[at] == y
        assert at == len(kept)
