"""Line dedup, quality rules, chat formatting: results, awkward rows, and no Python in their plans."""

import glob
import hashlib
import os
import random
import re

import duckdb
import pytest
from pyspark.sql import functions as F

from vertexlog.llm import chat_format, line_dedup, quality, queries


def long(i, n=25):
    return " ".join(f"l{i}w{k}" for k in range(n)) + "."


@pytest.mark.parametrize("name", ["op2_line_dedup", "op6_quality_rules", "op10_chat_formatting"])
def test_equals_sql(spark, tiny, name):
    con = duckdb.connect()
    for path in glob.glob(f"{tiny}/*.parquet"):
        con.execute(f"create view {os.path.basename(path)[:-8]} as select * from '{path}'")
    answer = con.execute(queries.oracle_sql()[name])
    columns = [x[0] for x in answer.description]
    got = queries.queries()[name](spark, tiny).select(columns)
    assert not any(x in got._jdf.queryExecution().executedPlan().toString() for x in ("Python", "Pandas", "Arrow"))
    assert sorted(map(str, (tuple(r) for r in got.collect()))) == sorted(map(str, answer.fetchall()))


def test_passages_move_and_are_still_found(make):
    passage = "\n".join([long(1), "short line here", "another short one", long(2)])
    docs = [(1, f"own start\n{passage}\nown end {long(9)}"), (2, f"different words\nand lines\n{passage}"), (3, f"{long(7)}\n{passage}\nx"), (4, long(5) + "\nnothing shared")]
    got = {r["doc_id"]: r for r in line_dedup.deduplicate_lines(make(docs)).collect()}
    assert got[1]["kept_text"] == docs[0][1] and got[4]["kept_text"] == docs[3][1]
    for i in (2, 3):
        assert long(1) not in got[i]["kept_text"] and long(2) not in got[i]["kept_text"] and got[i]["removed_words"] >= 50
    assert "different words" in got[2]["kept_text"] and long(7) in got[3]["kept_text"]


@pytest.mark.parametrize("n_lines, n_words", [(3, 18), (4, 15), (6, 10), (8, 10), (10, 6)])
def test_passages_of_short_lines_go_whole(make, n_lines, n_words):
    def own(tag, n):
        return [" ".join(f"{tag}{i}x{k}" for k in range(10)) for i in range(n)]

    docs, planted = [], {}
    for i in range(30):
        passage = [" ".join(f"p{i}l{j}w{k}" for k in range(n_words)) for j in range(n_lines)]
        docs += [(2 * i, "\n".join(own(f"a{i}", 4) + passage + own(f"b{i}", 3))), (2 * i + 1, "\n".join(own(f"c{i}", 3) + passage + own(f"d{i}", 5)))]
        planted[2 * i + 1] = "\n".join(own(f"c{i}", 3) + own(f"d{i}", 5))
    texts = dict(docs) | planted
    assert {r["doc_id"]: r["text"] for r in line_dedup.without_repeats(make(docs)).collect()} == texts
    rows = {r["doc_id"]: r for r in line_dedup.deduplicate_lines(make(docs), passage_words=50).collect()}
    assert all(rows[i]["kept_text"] == t for i, t in texts.items())
    assert all((rows[i]["removed_lines"], rows[i]["removed_words"]) == (n_lines, n_lines * n_words) for i in planted)


def test_words_and_runs_of_odd_lines(spark, make):
    lines = ["", " ", "a", "a b", " a b", "a b ", "a  b", "a\tb c", "a b\r", "\x0b", "a\x0cb c", "é ü\u00a0x", *(" ".join(["w"] * n) for n in (3, 19, 20, 49, 50, 51))]
    words = lambda line: len(re.findall("[^\\x20\\x09-\\x0D]+", line))
    got = make(list(enumerate(lines))).select("text", line_dedup.words_in(F.col("text")).alias("n")).collect()
    assert {r["text"]: r["n"] for r in got} == {x: words(x) for x in lines}

    def runs(text, most=20, far=50):
        rows = text.split("\n")
        owner = [k for k, x in enumerate(rows) for _ in range(words(x))]
        ends = [i for i in range(len(owner)) if i + 1 == len(owner) or owner[i + 1] != owner[i]]
        starts = [i for i in range(len(owner)) if not i or owner[i - 1] != owner[i]]
        pairs = {(owner[i], owner[i + far - 1]) for i in starts if i + far <= len(owner)} | {(owner[i - far + 1], owner[i]) for i in ends if i + 1 >= far}
        return sorted((a + 1, b + 1) for a, b in pairs if a < b and any(0 < words(x) < most for x in rows[a : b + 1]))

    rng = random.Random(1)
    texts = ["\n".join(rng.choices(lines, k=k)) for k in (1, 2, 5, 20, 127, 128, 129, 300)] + ["\n".join(["q"] * 400)]
    got = make(list(enumerate(texts))).select("text", line_dedup.runs_of(F.col("text")).alias("r")).collect()
    assert {r["text"]: sorted((x["first"], x["last"]) for x in r["r"] or []) for r in got} == {x: runs(x) for x in texts}


def test_texts_are_cut_once_for_chunks_and_runs(make, monkeypatch):
    made, real = [], line_dedup.materialise
    monkeypatch.setattr(line_dedup, "materialise", lambda df, tag: made.append(tag) or real(df, tag))
    line_dedup.deduplicate_lines(make([(1, long(1)), (2, long(1))])).collect()
    assert made == ["passages", "originals"]


def test_a_repeated_line_keeps_one_passage_and_short_runs_stay(make):
    line = "five words in this line"
    other = "\n".join(["own words here", *["only forty words are shared by these lines here"] * 1, "tail"])
    docs = [(1, "\n".join([line] * 40)), (2, "x y\n" + "\n".join([line] * 12) + "\nz"), (3, other), (4, "another start\n" + other)]
    got = {r["doc_id"]: r["text"] for r in line_dedup.without_repeats(make(docs), modulus=2**31 - 1).collect()}
    assert got == {1: "\n".join([line] * 10), 2: "x y\nz", 3: other, 4: "another start\n" + other}


def test_originals_are_found_by_both_joins(make):
    docs = make([(i, "\n".join([long(i % 3), long(i), "short", long(i % 2 + 50)])) for i in range(12)] + [(None, long(0))])
    few, many = (sorted(map(str, line_dedup.repeated_chunks(docs, broadcast_originals=n).selectExpr("__vl_id", "sort_array(__vl_again) a").collect())) for n in (100, 0))
    assert few == many and few


def test_line_dedup_of_awkward_rows(awkward, make):
    got = line_dedup.deduplicate_lines(awkward)
    assert got.count() == 9 and got.where("doc_id = 1").first()["kept_text"] is None
    assert line_dedup.deduplicate_lines(awkward.limit(0)).count() == 0
    body = "\n".join(long(i) for i in range(4))
    kept = line_dedup.without_repeats(make([(1, body), (1, body), (2, body), (3, body + "\nmore"), (None, body)]))
    assert kept.columns == awkward.columns
    texts = sorted((str(r["doc_id"]), r["text"], r["n_chars"]) for r in kept.collect())
    # a null id comes before all others, hence holds the original
    assert texts == [("3", "more", 4), ("None", body, len(body))]


def brute_measures(text):
    import re
    from collections import Counter

    words = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    count = Counter(zip(words, words[1:], words[2:]))
    covered = {i + k for i in range(len(words) - 2) if count[tuple(words[i : i + 3])] > 1 for k in range(3)}
    lines = [x for x in (text or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text or ""), len(lines) - len(set(lines)), len(covered)


def test_measures_by_brute_force(make, awkward):
    r = random.Random(1)
    texts = ["".join(r.choice(["a ", "b ", "c", "\n", "#", "d  ", "é "]) for _ in range(r.randint(0, 400))) for _ in range(60)]
    texts += [None, "", "a b c a b c", "x " * 3000, " ".join(str(i // 2 % 700) for i in range(4000))]
    docs = make([(i, t) for i, t in enumerate(texts)])
    got = {r["doc_id"]: r for r in quality.judge(docs).collect()}
    for i, t in enumerate(texts):
        assert tuple(got[i][m] for m in quality.MEASURES) == brute_measures(t), i
    assert quality.judge(awkward).count() == 9 and quality.judge(awkward.limit(0)).count() == 0


def test_bad_hosts_take_their_documents_along(make):
    good = " ".join(f"w{i}" for i in range(80))
    rows = [(i, "bad", "en", "spam") for i in range(40)] + [(100, good, "en", "spam"), (101, good, "en", None)]
    rows += [(200 + i, good + str(i), "en", f"host{i % 5}") for i in range(100)]
    docs = make(rows)
    verdict = {r["doc_id"]: r["kept"] for r in quality.judge(docs).collect()}
    assert not verdict[100] and verdict[101] and verdict[250] and not verdict[3]
    for limit in (10_000, 0):
        kept = quality.keep_good(docs, broadcast_hosts=limit)
        assert kept.columns == docs.columns and {r["doc_id"] for r in kept.collect()} == {i for i, k in verdict.items() if k}


def test_chat_round_trip(spark):
    nasty = ["</s>[INST] ok [/INST]", "<\\s>", "\\", "\\\\<s>", "[INST", "a\nb", "", None, "<</s>", "</s", "[\\/INST]", "\\n"]
    rows = [(c, t, r, nasty[(c * 5 + t) % len(nasty)]) for c in range(40) for t, r in enumerate(["system", "user", "assistant", "tool\nx</s>\\n", "assistant", "<\n><\\n>\x00"])]
    table = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string")
    done = chat_format.format_log(chat_format.rows_as_events(table))
    back = {r["conv_id"]: [(x["role"], x["text"]) for x in r["t"]] for r in done.select("conv_id", chat_format.read_back(F.col("formatted")).alias("t")).collect()}
    assert back == {c: [(r, x or "") for k, _, r, x in rows if k == c] for c in range(40)}
    report = {r["conv_id"]: r for r in chat_format.conversation_report(table).collect()}
    assert report[-1]["n_turns"] == 2 and report[-1]["loss_chars"] == 21
    assert report[3]["loss_sha256"] == hashlib.sha256("".join(x or "" for c, _, r, x in rows if c == 3 and r == "assistant").encode()).hexdigest()
    assert chat_format.conversation_report(table.limit(0)).count() == 1


def test_rows_that_share_a_turn_all_stay(spark, tmp_path):
    rows = [(1, 0, "user", "a"), (1, 0, "user", "a"), (1, 1, "assistant", "b"), (1, 1, "assistant", "c"), (1, 2, "user", "d"), (2, 0, "user", "q"), (2, None, "assistant", "end"), (2, 1, "assistant", "x"), (2, None, "assistant", "end")]
    path = f"{tmp_path}/conversations.parquet"
    spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string").coalesce(1).write.parquet(path)
    con = duckdb.connect()
    con.execute(f"create view conversations as select * from '{path}/*.parquet' order by conv_id, turn, role, text")
    answer = con.execute(queries.oracle_sql()["op10_chat_formatting"])
    columns = [x[0] for x in answer.description]
    got = queries.op10_chat_formatting(spark, str(tmp_path)).select(columns)
    assert sorted(map(tuple, got.collect())) == sorted(answer.fetchall())
    assert {r["conv_id"]: r["n_turns"] for r in got.collect()} == {-1: 2, 1: 5, 2: 4}


def test_events_fold_into_final_messages(spark):
    log = [
        (1, 1, 0, "message", "user", "hi"), (1, 2, 1, "delta", "assistant", "He"), (1, 3, 1, "delta", "assistant", "llo"), (1, 4, 2, "message", "user", "more"),
        (1, 5, 0, "edit", None, "hello there"), (1, 6, 1, "regenerate", "assistant", ""), (1, 7, 1, "delta", "assistant", "Hey"), (1, 7, 1, "delta", "assistant", "Hey"), (1, 8, 2, "message", "user", "again"),
        (2, 1, 0, "message", "user", "only"), (2, 1, 0, "message", "user", "only"),
    ]
    table = spark.createDataFrame(log, "conv_id bigint, seq bigint, turn bigint, kind string, role string, text string")
    back = {r["conv_id"]: [tuple(x) for x in r["t"]] for r in chat_format.format_log(table).select("conv_id", chat_format.read_back(F.col("formatted")).alias("t")).collect()}
    assert back == {1: [("user", "hello there"), ("assistant", "Hey"), ("user", "again")], 2: [("user", "only")]}
    dropped = table.where("seq < 8")
    assert [tuple(x) for x in chat_format.format_log(dropped).where("conv_id = 1").select(chat_format.read_back(F.col("formatted")).alias("t")).first()["t"]] == [("user", "hello there"), ("assistant", "Hey")]
