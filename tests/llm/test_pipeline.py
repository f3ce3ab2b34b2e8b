"""The pipeline's stages take effect, keep clean documents, and equal plain Python on a small table."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import xxhash
from tokenizers import Tokenizer

import corpus_pipeline
from vertexlog.llm import packing


def test_stages_in_order(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    start = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, docs, tiny)
        assert after.schema.fieldNames() == docs.schema.fieldNames(), name
        rows = after.collect()
        docs = spark.createDataFrame(rows, start.schema)
        assert rows and len(rows) <= start.count()
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, tiny)
    assert {r["doc_id"] for r in packed.collect()} == {r["doc_id"] for r in docs.collect()}


def test_run_returns_the_last_stage(spark, tiny):
    out = corpus_pipeline.run(spark, tiny)
    assert set(packing.PIECE.replace(" int", "").replace(" bigint", "").split(", ")) <= set(out.columns) and out.count() > 0


def test_clean_documents_stay(spark, make):
    from vertexlog.llm import decontaminate, line_dedup, quality, simhash

    texts = [(i, "\n".join(" ".join(f"d{i}l{k}w{j}" for j in range(30)) for k in range(4))) for i in range(20)]
    docs = make(texts)
    bench = spark.createDataFrame([(1, " ".join(f"q{i}" for i in range(30)))], "item_id bigint, text string")
    for kept in (quality.keep_good(docs), line_dedup.without_repeats(docs), simhash.keep_one_of_each(docs), decontaminate.remove_contaminated(docs, bench)):
        assert sorted((r["doc_id"], r["text"]) for r in kept.collect()) == texts


SPACE = " \t\n\x0b\f\r"


def split(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def order(i):
    return (i is not None, i or 0)


def brute_quality(docs):
    def failed(text):
        w = split(text)
        count = Counter(zip(w, w[1:], w[2:]))
        again = {i + k for i in range(len(w) - 2) if count[tuple(w[i : i + 3])] > 1 for k in range(3)}
        return len(w) < 50 or 100 * len(again) > 50 * len(w)

    hosts = defaultdict(list)
    for d in docs:
        hosts[d["source"]].append(failed(d["text"]))
    rates = [sum(x) / len(x) for x in hosts.values()]
    m = sum(rates) / max(1, len(rates))
    v = sum((r - m) ** 2 for r in rates) / (len(rates) - 1) if len(rates) > 1 else 0.0
    w = m * (1 - m) / v - 1 if v > 0 and m * (1 - m) > v else 20.0
    bad = {h for h, x in hosts.items() if (sum(x) + m * w) / (len(x) + w) > 0.6}
    return [d for d in docs if not failed(d["text"]) and d["source"] not in bad]


def brute_lines(docs):
    def cut(text):
        lines = text.split("\n")
        n, h = [len(split(x)) for x in lines], [int(hashlib.md5(x.encode()).hexdigest()[:8], 16) for x in lines]
        starts = [i for i in range(len(lines)) if i == 0 or n[i] >= 20 or n[i - 1] >= 20 or (h[i - 1] * 31 + (h[i - 2] if i > 1 else 0)) % 2147483647 % 4 == 0]
        return [(a, b, "\n".join(lines[a:b]), sum(n[a:b])) for a, b in zip(starts, [*starts[1:], len(lines)], strict=True)]

    def runs(text):
        lines = text.split("\n")
        n = [len(split(x)) for x in lines]
        owner, out = [i for i, k in enumerate(n) for _ in range(k)], set()
        for p in range(len(owner) - 49):
            a, b = owner[p], owner[p + 49]
            edge = p == 0 or owner[p - 1] != a or p + 50 == len(owner) or owner[p + 50] != b
            if a < b and edge and any(0 < k < 20 for k in n[a : b + 1]):
                out.add((a, b, "\n".join(lines[a : b + 1])))
        return out

    chunks, passages = defaultdict(set), defaultdict(list)
    for d in docs:
        if d["text"] is not None:
            for no, (a, b, body, words) in enumerate(cut(d["text"])):
                if words and (b - a > 1 or words >= 20):
                    chunks[body].add((order(d["doc_id"]), no))
            for a, b, body in runs(d["text"]):
                passages[body].append((order(d["doc_id"]), a, b))
    out = []
    for d in docs:
        if d["text"] is None:
            out.append(d)
            continue
        i, lines, gone = order(d["doc_id"]), d["text"].split("\n"), set()
        for no, (a, b, body, _) in enumerate(cut(d["text"])):
            if (i, no) in chunks[body] and (i, no) != min(chunks[body]):
                gone |= set(range(a, b))
        for a, b, body in runs(d["text"]):
            first = min(passages[body])
            if len(passages[body]) > 1 and (first[0] != i or a > first[2]):
                gone |= set(range(a, b + 1))
        text = "\n".join(x for k, x in enumerate(lines) if k not in gone)
        if not gone:
            out.append(d)
        elif text.strip(SPACE):
            out.append({**d, "text": text, "n_chars": len(text)})
    return out


def brute_near(docs):
    def print_of(text):
        words = [w.lower() for w in (text or "").encode().split()]
        if not words:
            return 0
        hashes = [xxhash.xxh64_intdigest(b" ".join(words[i : i + 4]), 42) for i in range(max(1, len(words) - 3))]
        return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))

    prints = [print_of(d["text"]) for d in docs]
    label = list(range(len(docs)))
    for a in range(len(docs)):
        for b in range(a):
            if (prints[a] ^ prints[b]).bit_count() <= 4 and label[a] != label[b]:
                label = [label[b] if x == label[a] else x for x in label]
    least = {}
    for d, x in zip(docs, label, strict=True):
        if d["doc_id"] is not None:
            least[x] = min(least.get(x, d["doc_id"]), d["doc_id"])
    gone = {d["doc_id"] for d, x in zip(docs, label, strict=True) if d["doc_id"] is not None and least[x] < d["doc_id"]}
    return [d for d in docs if d["doc_id"] not in gone]


def brute_clean(docs, items):
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    windows = {tuple(w[i : i + 13]) for w in map(words, items) if w for i in range(max(1, len(w) - 12))}
    out = []
    for d in docs:
        w, hit = words(d["text"]), set()
        for n in {len(x) for x in windows}:
            for i in range(len(w) - n + 1):
                if tuple(w[i : i + n]) in windows:
                    hit |= set(range(i, i + n))
        if not (hit and 20 * len(hit) >= len(w)):
            out.append(d)
    return out


def brute_pieces(docs):
    whole, out = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json")), []
    for d in docs:
        ids = [*whole.encode(d["text"] or "", add_special_tokens=False).ids, 0]
        first = len(ids) % 2048 or 2048
        for piece, (a, b) in enumerate(zip([0, *range(first, len(ids), 2048)], [*range(first, len(ids), 2048), len(ids)], strict=True)):
            out.append((str(d["doc_id"]), piece, a, b - a, zlib.crc32(np.array(ids[a:b], "<u4").tobytes())))
    return sorted(out)


def corpus(make):
    """Hosts good and bad, copies, near copies, shared passages of long and of short lines, benchmark text, odd rows."""
    r = random.Random(12)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(r.randint(2, 7)))
    line = lambda n: " ".join(word() for _ in range(n))
    item = line(40)
    long_passage, short_passage = "\n".join(line(25) for _ in range(3)), "\n".join(line(9) for _ in range(7))
    rows = []
    for i in range(60):
        body = [line(r.randint(4, 30)) for _ in range(r.randint(4, 9))]
        if i % 6 == 1:
            body.insert(r.randrange(len(body)), long_passage)
        if i % 6 == 2:
            body.insert(r.randrange(len(body)), short_passage)
        if i % 10 == 3:
            body[0] = item.upper()
        rows.append((i, "\n".join(body), "en", f"host{i % 5}"))
    for i in range(10):
        words = rows[i][1].split(" ")
        words[len(words) // 2] = "changed"
        rows += [(100 + i, " ".join(words), "en", "host1"), (200 + i, rows[i][1], "en", "host2")]
    rows += [(300 + i, "too short", "en", "spam") for i in range(30)] + [(340, line(80), "en", "spam"), (341, " ".join(["a b c"] * 40), "en", "host3")]
    rows += [(400, None), (401, ""), (402, " \t\n"), (None, line(90)), (None, rows[5][1]), (403, line(300), None, None), (403, line(300), None, None), (5, rows[5][1], "en", "host0"), (404, "\n".join([line(4)] * 3 + [line(60)]))]
    for i in range(4):  # one line of many words, one of them changed: nothing for line dedup, near copies all the same
        words = line(900).split(" ")
        rows += [(500 + 10 * i + k, " ".join(words[:k] + ["other"] * (k > 0) + words[k + 1 :]), "en", f"host{k}") for k in range(3)]
    return make(rows), [item, None, "", line(5)]


def as_rows(frame, columns):
    return sorted(tuple(str(d[c]) for c in columns) for d in frame)


def test_every_stage_equals_brute_force(spark, make, tmp_path):
    docs, items = corpus(make)
    docs = docs.repartition(5)
    spark.createDataFrame(list(enumerate(items)), "item_id bigint, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    now, columns = [x.asDict() for x in docs.collect()], docs.columns
    plain = [brute_quality, brute_lines, brute_near, lambda d: brute_clean(d, items)]
    for (name, stage), brute in zip(corpus_pipeline.STAGES, plain, strict=False):
        after = stage(spark, spark.createDataFrame(now, docs.schema).repartition(3), str(tmp_path))
        assert after.columns == columns
        got, want = [x.asDict() for x in after.collect()], brute(now)
        assert as_rows(got, columns) == as_rows(want, columns), name
        assert 0 < len(want) and as_rows(want, columns) != as_rows(now, columns), name
        now = want
    packed = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert sorted((str(x["doc_id"]), x["piece"], x["start"], x["length"], x["ids_crc32"]) for x in packed) == brute_pieces(now)
    held = defaultdict(list)
    for x in packed:
        held[x["sequence_id"]].append((x["offset"], x["length"]))
    for parts in held.values():
        assert [a for a, _ in sorted(parts)] == [sum(n for _, n in sorted(parts)[:k]) for k in range(len(parts))] and sum(n for _, n in parts) <= 2048
    bins: list[int] = []
    for n in sorted((x["length"] for x in packed), reverse=True):
        k = next((k for k, room in enumerate(bins) if room >= n), None)
        bins.append(2048 - n) if k is None else bins.__setitem__(k, bins[k] - n)
    assert len(held) <= 1.02 * len(bins) + 1


def test_an_empty_table_passes_all_stages(spark, make, tmp_path):
    make([(1, "x")]).limit(0).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([], "item_id bigint, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
