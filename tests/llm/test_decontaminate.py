import hashlib
import random
import re

import duckdb

from vertexlog.llm import decontaminate as d
from vertexlog.llm import queries

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def lower(text):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")


def brute(docs, items, window=13):
    out = {}
    for i, text in docs:
        words = WORD.findall(lower(text))
        hit, found = set(), set()
        for item, body in items:
            w = WORD.findall(lower(body))
            n = min(window, len(w))
            for a in range(len(w) - n + 1) if n else ():
                for b in range(len(words) - n + 1):
                    if words[b : b + n] == w[a : a + n]:
                        hit |= set(range(b, b + n))
                        found.add(str(item))
        digest = hashlib.sha256(",".join(sorted(found)).encode()).hexdigest()
        out[i] = (len(words), len(hit), len(found), digest, bool(hit) and 20 * len(hit) >= len(words))
    return out


def random_case(seed):
    r = random.Random(seed)
    word = lambda: r.choice("ab") * r.randint(1, 2) + r.choice(["", "É", "7", "'"])
    items = [(i, " ".join(word() for _ in range(r.choice([0, 1, 2, 5, 13, 14, 20])))) for i in range(25)] + [(100, None)]
    docs = [(i, " ".join(word() for _ in range(r.randint(0, 120))) + (" " + r.choice(items[:-1])[1] if i % 3 else "")) for i in range(40)]
    return docs, items


def test_equals_brute_force(spark, make):
    docs, items = random_case(3)
    bench = spark.createDataFrame(items, "item_id bigint, text string")
    got = d.contamination_report(make(docs), bench).collect()
    assert {r["doc_id"]: (r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"], r["contaminated"]) for r in got} == brute(docs, items)


def test_benchmark_beyond_one_block_gives_the_same(spark, make):
    docs, items = random_case(4)
    bench = spark.createDataFrame(items, "item_id bigint, text string")
    one, many = (sorted(map(tuple, d.contamination_report(make(docs), bench, block_bytes=b).collect())) for b in (1 << 25, 64))
    assert one == many


def test_awkward_rows_and_empty_tables(spark, awkward):
    bench = spark.createDataFrame([(1, "same text here"), (None, "a null id")], "item_id bigint, text string")
    got = d.contamination_report(awkward, bench).collect()
    assert len(got) == 9
    assert sorted(r["n_hit"] for r in got) == [0, 0, 0, 0, 0, 3, 3, 3, 3]
    assert d.contamination_report(awkward.limit(0), bench).count() == 0
    assert d.contamination_report(awkward, bench.limit(0)).where("n_hit > 0").count() == 0
    kept = d.remove_contaminated(awkward, bench)
    assert kept.columns == awkward.columns and kept.count() == 5


def test_query_equals_sql(spark, tiny):
    con = duckdb.connect()
    for name in ("documents", "benchmark"):
        con.execute(f"create view {name} as select * from '{tiny}/{name}.parquet'")
    answer = con.execute(queries.oracle_sql()["op1_benchmark_decontamination"])
    got = queries.op1_benchmark_decontamination(spark, tiny).select([x[0] for x in answer.description])
    assert sorted(map(tuple, got.collect())) == sorted(answer.fetchall())
