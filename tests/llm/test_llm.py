"""Operators of the corpus pipeline against brute force, on a small fixture with every odd case."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

FOLD = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, n_words long, row long"


def _texts():
    rng = random.Random(5)
    pools = {"en": "the and of to in is that with for was on".split(), "de": "der die und ist nicht mit den von für über".split()}
    pools["ru"] = "и в не на что это как для с по".split()

    def prose(lang, n):
        return " ".join("".join(rng.sample(pools[lang], 2)) if rng.random() < 0.5 else rng.choice(pools[lang]) for _ in range(n))

    out = []
    for i in range(40):
        lang = rng.choice(list(pools))
        out.append((prose(lang, rng.randrange(20, 120)), lang))
    base = prose("en", 200)
    words = base.split()
    out += [(base, "en"), (base, "en"), (base.upper(), "en"), (" ".join(words[:190] + ["x"] * 10), "en"), (" ".join(["y"] * 3 + words[3:]), None)]
    out += [(None, "en"), (None, None), ("", "de"), ("   \n\t ", "en"), ("a", "en"), ("a b", "en"), ("A B", "en"), ("12 34 !!", "de")]
    out += [("ab\n" * 80, "en"), ("ab\n" * 80 + "c", "en"), ("aaaa" * 100, "en"), ("| " * 400, "en"), ("x" * 99, "en"), ("x" * 100, "en"), ("x" * 101, "en")]
    out += [(prose("en", 6000), "en"), ("das ist 中文 текст ½   <|endoftext|> it's we're o'lls ''s 's", "de")]
    out += [(prose("en", 30) + " # * $ % & | < > line\nsame line\nsame line\n\n", "en")]
    return out


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(9)
    out = []
    for i, (t, lang) in enumerate(_texts()):
        source = rng.choice(["a", "b", "hot", "hot", "hot", None])
        out.append((i * 3, t, lang, source, len(t or ""), 1, 2, 3))
    return out


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def _by_id(df):
    got = {r["doc_id"]: r.asDict() for r in df.collect()}
    return got


def folded(t):
    return WORD.findall((t or "").translate(FOLD))


def test_host_rules(docs, rows, empty):
    from softsplit.llm.host_rules import host_quality

    got = _by_id(host_quality(docs))
    assert len(got) == len(rows)
    for i, t, *_ in rows:
        t = t or ""
        ws = WORD.findall(t)
        grams = Counter(tuple(ws[j : j + 8]) for j in range(len(ws) - 7))
        hit = {k for j in range(len(ws) - 7) if grams[tuple(ws[j : j + 8])] > 1 for k in range(j, j + 8)}
        lines = [x for x in t.split("\n") if WORD.search(x)]
        want = (len(ws), sum(map(len, ws)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(hit))
        r = got[i]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == want, (i, t[:50])
        assert r["base_failed"] == (len(ws) < 20 or 100 * len(hit) > 30 * len(ws))
        assert not (r["base_failed"] and r["kept"])
    assert host_quality(empty).count() == 0


def test_host_verdict_rejects_a_bad_host(spark):
    from softsplit.llm.host_rules import host_quality

    good, bad = " ".join(f"word{k}" for k in range(40)), "too short"
    rows = [(i, good if i % 10 or i >= 300 else bad, "good") for i in range(600)] + [(1000 + i, bad if i % 5 else good, "bad") for i in range(200)]
    got = _by_id(host_quality(spark.createDataFrame(rows, "doc_id long, text string, source string")))
    assert got[1]["kept"] and not got[1000]["kept"] and not got[1000]["base_failed"]


def test_near_dedup(docs, rows, empty):
    from softsplit.llm.near_dedup import near_components

    sets = {}
    for i, t, *_ in rows:
        ws = folded(t)
        sets[i] = {tuple(ws[j : j + 5]) for j in range(len(ws) - 4)} if len(ws) >= 5 else ({tuple(ws)} if ws else set())
    parent = {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in sets:
        for b in sets:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    for kw in ({}, {"node_size": 2, "depth": 2, "cluster_size": 2, "small_members": 0}):
        got = _by_id(near_components(docs, **kw))
        assert {i: (r["n_shingles"], r["component_id"], r["kept"]) for i, r in got.items()} == {i: (len(sets[i]), find(i), find(i) == i) for i in sets}
    assert near_components(empty).count() == 0


def test_near_dedup_large_groups_and_repeated_ids(spark):
    from softsplit.llm.near_dedup import near_components

    base = [f"w{k}" for k in range(200)]
    rows = [(i, " ".join(base[:199] + [f"own{i}"])) for i in range(1, 121)] + [(500 + i, " ".join(f"n{i}x{k}" for k in range(50))) for i in range(20)]
    rows += [(7, "short text"), (7, "another text here"), (900, "another text here"), (None, "short text")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = near_components(df, node_size=16, depth=1, cluster_size=25).collect()
    assert all(r["component_id"] == 1 for r in got if r["doc_id"] is not None and (r["doc_id"] <= 120 or r["doc_id"] == 900))
    assert all(r["kept"] for r in got if r["doc_id"] is not None and 500 <= r["doc_id"] < 520)
    assert [r["kept"] for r in got if r["doc_id"] is None] == [True]


def test_decontaminate(spark, docs, rows, empty):
    from softsplit.llm.decontaminate import contamination

    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    words = lambda t: word.findall((t or "").translate(FOLD))
    long = next(t for _, t, *_ in rows if t and len(t) > 20000)
    items = [(1, " ".join(long.split()[100:115])), (2, "a b"), (3, None), (4, "!!"), (10, "AB ab Ab aB"), (11, rows[0][1]), (12, "x" * 100), (None, "a"), (1, "der die und")]
    table = spark.createDataFrame(items, "item_id long, text string")
    for kw in ({}, {"block": 3}):
        got = _by_id(contamination(docs, table, **kw))
        for i, t, *_ in rows:
            ws, hit, found = words(t), set(), set()
            for item, text in items:
                iw = words(text)
                n = min(10, len(iw))
                wins = {tuple(iw[k : k + n]) for k in range(len(iw) - n + 1)} if n else set()
                for k in range(len(ws) - n + 1 if n else 0):
                    if tuple(ws[k : k + n]) in wins:
                        hit |= set(range(k, k + n))
                        found |= {str(item)} - {"None"}
            want = (len(ws), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit))
            r = got[i]
            assert (r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"], r["contaminated"]) == want, (i, (t or "")[:40])
    assert contamination(empty, table).count() == 0
    assert not any(r["contaminated"] for r in contamination(docs, table.limit(0)).collect())


def test_mixing(spark, docs, rows, empty):
    from softsplit.llm.mixing import mix

    got = _by_id(mix(docs))
    size = {i: len(WORD.findall(t or "")) for i, t, *_ in rows}
    source = {i: s for i, _, _, s, *_ in rows}
    total = defaultdict(int)
    for i in size:
        total[source[i]] += size[i]
    names = sorted([s for s in total if s is not None]) + [None] * (None in total)
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(names)}
    target, left, open_ = {}, 1.5 * sum(total.values()), set(names)
    while open_:
        unit = left / sum(weight[s] for s in open_)
        over = {s for s in open_ if unit * weight[s] > 2 * total[s]}
        for s in over or open_:
            target[s] = 2.0 * total[s] if over else unit * weight[s]
        left -= sum(target[s] for s in over)
        open_ -= over or open_
    taken = defaultdict(int)
    for i, r in got.items():
        assert r["size"] == size[i] and r["source_size"] == total[source[i]] and math.isclose(r["target"], target[source[i]], rel_tol=1e-9)
        assert r["taken"] == r["copies"] * size[i] <= 2 * size[i]
        taken[source[i]] += r["taken"]
    for s in names:
        assert abs(taken[s] - target[s]) <= max(size[i] for i in size if source[i] == s)
    again = _by_id(mix(docs.repartition(5)))
    assert {i: r["taken"] for i, r in got.items()} == {i: r["taken"] for i, r in again.items()}
    assert mix(empty).count() == 0


def test_pivotal_keeps_expectation_over_seeds(spark):
    from softsplit.llm._store import Workspace
    from softsplit.llm.mixing import pivotal

    units = spark.range(300).selectExpr("1 AS sid", "id AS uid", "xxhash64(id) AS h", "CAST(1 + id % 7 AS double) AS n", "0.3D AS p").cache()
    counts = np.zeros(300)
    for seed in range(12):
        take = pivotal(units, Workspace(spark, "test"), seed, block=16).collect()
        assert len(take) == 300
        words = sum((1 + r["uid"] % 7) * r["take"] for r in take)
        assert abs(words - 0.3 * sum(1 + i % 7 for i in range(300))) < 7
        for r in take:
            counts[r["uid"]] += r["take"]
    assert abs(counts.mean() / 12 - 0.3) < 0.03


def test_token_shards(docs, rows, empty, spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    from softsplit.llm.token_shards import token_files

    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    for kw in ({}, {"shard_tokens": 500, "partitions": 2}):
        got, start = _by_id(token_files(docs, **kw)), 0
        for i, t, *_ in rows:
            ids = tok.encode(t or "", add_special_tokens=False).ids + [0]
            r = got[i]
            assert (r["start"], r["n_tokens"], r["ids_crc32"]) == (start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())), (i, t)
            start += len(ids)
    assert token_files(empty).count() == 0
    twice = spark.createDataFrame([(None, "n"), (5, "b"), (5, "a"), (1, None)], "doc_id long, text string")
    assert sorted((r["start"], r["doc_id"]) for r in token_files(twice).collect()) == [(0, None), (2, 1), (3, 5), (5, 5)]


def test_piece_table_grows():
    import signal

    import public_tokenizers

    from softsplit.llm.token_shards import Encoder, PieceTable

    def stop(*_):
        raise TimeoutError("the table is full and the look-up never ends")

    before = signal.signal(signal.SIGALRM, stop)
    signal.alarm(60)
    try:
        table = PieceTable(bits=4)
        h = np.random.default_rng(3).integers(1, 2**63, 5000).astype(np.uint64)
        for part in (h[:9], h[9:40], h[40:]):
            table.add(part)
        assert (table.find(h) == np.arange(5000)).all() and (table.find(h + np.uint64(1)) == -1).all()
        encoder = Encoder(public_tokenizers.path("byte_bpe_50k.json"))
        encoder.known = PieceTable(bits=4)
        text = " ".join(f"w{i * 7919 % 1000}x" for i in range(2000))
        ids, _ = encoder.encode(pa.array([text]))
        assert ids.tolist() == encoder.tokenizer.encode(text, add_special_tokens=False).ids + [0]
    finally:
        signal.alarm(0)
        signal.signal(signal.SIGALRM, before)


def test_wavelet_matrix():
    from softsplit.llm.token_shards import WaveletMatrix, pack, unpack

    rng = np.random.default_rng(1)
    for n, top in ((0, 8), (1, 8), (513, 8), (5000, 50257)):
        ids = rng.integers(0, top, n)
        ids[: n // 2] %= 5
        w = WaveletMatrix.build(ids, 16)
        w, doc_ids, lengths = unpack(pack(w, pa.array([1, None], pa.int64()), np.array([n, 0])))
        assert doc_ids.to_pylist() == [1, None] and lengths.tolist() == [n, 0]
        assert (w.decode() == ids).all()
        if n:
            at = rng.integers(0, n, 50)
            assert (w.access(at) == ids[at]).all()
        for s in (0, 3, 4, 7, 65536):
            lo, hi = sorted(rng.integers(0, n + 1, 2).tolist())
            assert w.count(s, lo, hi) == (ids[lo:hi] == s).sum()
            assert (w.occurrences(s) == np.flatnonzero(ids == s)).all()


def test_sharding(docs, rows, empty):
    from softsplit.llm.sharding import lpt, lpt_shards

    got = _by_id(lpt_shards(docs, 4))
    by_text, slots, load = defaultdict(set), defaultdict(list), Counter()
    for i, t, *_ in rows:
        r = got[i]
        assert r["size"] == len((t or "").encode()) + 16 and r["text_crc32"] == zlib.crc32((t or "").encode())
        by_text[t].add(r["shard"])
        slots[r["shard"]].append(r["slot"])
        load[r["shard"]] += r["size"]
    assert all(len(s) == 1 for s in by_text.values())
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    assert sorted(load) == [0, 1, 2, 3]
    assert lpt_shards(empty, 4).count() == 0
    assert lpt(np.array([5, 4, 3, 3, 3]), 2).tolist() == [0, 1, 1, 0, 1]


def test_sharding_balance_beside_a_plain_heap(spark, sf_dir):
    """The fullest of 40 shards holds at most a hundredth more than under a plain heap over all groups."""
    import heapq

    from softsplit.llm.sharding import lpt_shards

    table = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    groups = Counter()
    for r in table.collect():
        groups[r["text"]] += len((r["text"] or "").encode()) + 16
    heap = [0] * 40
    for size in sorted(groups.values(), reverse=True):
        heapq.heapreplace(heap, heap[0] + size)
    load = Counter()
    for r in lpt_shards(table, 40).collect():
        load[r["shard"]] += r["size"]
    assert sum(load.values()) == sum(heap) and len(load) == 40
    assert max(load.values()) <= 1.01 * max(heap)


def test_language_id(docs, rows, empty):
    from softsplit.llm.langid import language_id

    got = _by_id(language_id(docs))
    for i, t, lang, *_ in rows:
        r = got[i]
        assert r["held_out"] == (zlib.crc32(str(i).encode()) % 5 == 0) and 0 <= r["score"] <= 1
        if not t or not any(map(str.isalpha, t)):
            assert r["lang_pred"] == "und"
        else:
            assert r["lang_pred"] in {"en", "de", "ru"}
    prose = [(i, lang) for i, t, lang, *_ in rows[:40]]
    assert sum(got[i]["lang_pred"] == lang for i, lang in prose) >= 39
    assert language_id(empty).count() == 0


def test_viterbi_runs_agree_with_one_pass():
    from softsplit.llm.langid import viterbi

    rng = np.random.default_rng(0)
    for _ in range(20):
        n, sizes = int(rng.integers(1, 6)), rng.integers(0, 40, 8)
        at = np.concatenate([[0], np.cumsum(sizes)])
        s = (rng.normal(size=(at[-1], n)) * 3).astype(np.float32)
        got = viterbi(s, at, 2.0, run=int(rng.integers(3, 50)))
        for a, b in zip(at[:-1], at[1:]):
            if b > a:
                d = s[a].astype(float)
                for k in range(a + 1, b):
                    d = (d[:, None] - 2.0 * (1 - np.eye(n))).max(0) + s[k]
                own = got[a:b]
                value = s[np.arange(a, b), own].sum() - 2.0 * (np.diff(own) != 0).sum()
                assert abs(d.max() - value) < 1e-3


def test_language_spans(spark):
    from softsplit.llm.langid import label_texts, train

    en, ru = "the cat and the dog are here ", "кот и собака уже тут "
    model = train(spark.createDataFrame([(en, "en"), (ru, "ru")], "text string, lang string"))
    mixed = spark.createDataFrame([(1, en + ru * 3 + en)], "doc_id long, text string")
    spans = label_texts(mixed, model, spans=True).first()["spans"]
    assert [(s["word"], s["words"], s["lang"]) for s in spans] == [(0, 7, "en"), (7, 15, "ru"), (22, 7, "en")]


def test_suffix_dedup(docs, rows, empty):
    from softsplit.llm.suffix_dedup import remove_repeats

    got, seen = _by_id(remove_repeats(docs, budget=1 << 12, shard_bytes=1 << 14)), set()
    for i, t, *_ in rows:
        x = (t or "").encode()
        gone = bytearray(len(x))
        for j in range(len(x) - 99):
            if x[j : j + 100] in seen:
                gone[j : j + 100] = b"\1" * 100
            seen.add(x[j : j + 100])
        kept = bytes(b for b, g in zip(x, gone) if not g)
        r = got[i]
        assert (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) == (len(x), sum(gone), len(re.findall(b"\1+", bytes(gone))), hashlib.sha256(kept).hexdigest()), i
    assert remove_repeats(empty).count() == 0


def test_induced_sort():
    from softsplit.llm.induced_sort import sort_suffixes

    rng = random.Random(1)
    for _ in range(60):
        n, k = rng.choice([1, 2, 3, 10, 50, 300]), rng.choice([1, 2, 3, 20])
        t = np.array([rng.randrange(k) for _ in range(n)], np.uint16)
        if rng.random() < 0.4:
            t = np.concatenate([t, t, t])
        cap, out = rng.choice([5, 100]), []
        sort_suffixes(t, cap, lambda p, x: out.append((p, x)), budget=rng.choice([0, 1 << 20]))
        p, lcp = (np.concatenate(x) for x in zip(*out))
        b = t.tolist()
        assert [b[i : i + cap] for i in p] == [b[i : i + cap] for i in sorted(range(len(b)), key=lambda i: b[i:])]
        for j in range(1, len(p)):
            x, y = b[p[j - 1] :], b[p[j] :]
            c = next((m for m in range(min(len(x), len(y), cap)) if x[m] != y[m]), min(len(x), len(y), cap))
            assert c == lcp[j]


def test_maxent(docs, rows, empty):
    from softsplit.llm.maxent import score_texts

    got = _by_id(score_texts(docs))
    tokens = {i: [*folded(t), "\0end"] for i, t, *_ in rows}
    held = {i: zlib.crc32(str(i).encode()) % 7 == 2 for i in tokens}
    c = Counter()
    for i, ts in tokens.items():
        if not held[i]:
            c.update(ts)
    n, v = sum(c.values()), len(c)
    for i, ts in tokens.items():
        r = got[i]
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (held[i], len(ts), sum(c[t] > 0 for t in ts), n)
        assert math.isclose(r["base_score"], sum(math.log10((c[t] + 1) / (n + v + 1)) for t in ts), rel_tol=1e-9)
        assert math.isfinite(r["score"]) and r["score"] < 0
    assert score_texts(empty).count() == 0


def test_maxent_beats_unigrams_on_held_out_texts(spark, sf_dir):
    from softsplit.llm.maxent import score_texts

    got = score_texts(spark.read.parquet(f"{sf_dir}/documents.parquet")).filter("held_out").collect()
    assert got and sum(r["score"] for r in got) > sum(r["base_score"] for r in got)


def test_maxent_probabilities_sum_to_one():
    from softsplit.llm import maxent

    rng = np.random.default_rng(2)
    table = rng.normal(size=(maxent.ROWS, maxent.C)).astype(np.float32)
    top = np.arange(maxent.C * maxent.G, dtype=np.uint64) << np.uint64(64 - maxent.CLASS_BITS - maxent.GROUP_BITS)
    one = np.full(len(top), np.uint64(12345678901234567))
    p = 10 ** maxent.context_score(table, top, one, one * np.uint64(3))
    assert math.isclose(p.sum(), 1.0, rel_tol=1e-4)


def test_chat(spark, sf_dir):
    from softsplit.llm.chat import format_chats, units_of_lines

    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet")
    got = format_chats(turns).collect()
    assert len(got) == turns.count()
    majority = max(Counter(r["role"] for r in got).values())
    assert sum(r["role"] == r["role_pred"] for r in got) > 1.3 * majority  # a dozen conversations to learn from
    more = [r for r in format_chats(spark.read.parquet(f"{sf_dir}/../sf0.01/conversations.parquet")).collect() if r["held_out"]]
    assert sum(r["role"] == r["role_pred"] for r in more) >= 0.95 * len(more)
    same = {(r["conv_id"], r["turn"]): r["role_pred"] for r in got}
    assert same == {(r["conv_id"], r["turn"]): r["role_pred"] for r in format_chats(turns, chunk=2).collect()}
    odd = turns.select("conv_id", "turn", "role", "text").unionByName(
        spark.createDataFrame([(None, 0, "user", "hi"), (None, None, None, None), (9000, 0, None, "User: hello?"), (9000, 1, None, "")], "conv_id long, turn long, role string, text string")
    )
    odd_got = format_chats(odd.withColumn("code", odd["turn"])).collect()
    assert len(odd_got) == odd.count() and all(r["role_pred"] for r in odd_got)
    assert any(r["rendered"].endswith("|>\nhello?\n<|end|>\n") for r in odd_got)
    assert format_chats(turns.limit(0)).count() == 0
    lines = spark.createDataFrame([(1, "User: hi\n\nAssistant: hello\n")], "id long, text string")
    assert [r["text"] for r in units_of_lines(lines, "id", "text").orderBy("turn").collect()] == ["User: hi", "Assistant: hello"]


def test_pipeline_against_brute_force(spark, tmp_path, sf_dir):
    import corpus_pipeline

    from softsplit.llm.mixing import mix

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    kept = docs
    seen = []
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, kept, sf_dir).write.parquet(str(tmp_path / name))
        seen.append(kept)
        kept = spark.read.parquet(str(tmp_path / name))
    ids = [{r["doc_id"] for r in df.select("doc_id").collect()} for df in [*seen[1:], kept]]
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    quality, unique, clean, mixed, out = ids
    assert quality == {i for i, t in texts.items() if _passes(t)}
    shingles = {i: _shingles(texts[i]) for i in quality}
    for a in unique:
        for b in unique:
            assert a >= b or 100 * len(shingles[a] & shingles[b]) < 75 * len(shingles[a] | shingles[b])
    for a in quality - unique:
        assert any(100 * len(shingles[a] & shingles[b]) >= 75 * len(shingles[a] | shingles[b]) for b in quality if b != a)
    items = [r["text"] for r in spark.read.parquet(f"{sf_dir}/benchmark.parquet").collect()]
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", t.translate(FOLD))
    wins = {tuple(w[k : k + min(10, len(w))]) for w in map(words, items) for k in range(max(len(w) - 9, 1)) if w}
    dirty = lambda t: any(tuple(w[k : k + n]) in wins for n in {len(x) for x in wins} for w in [words(t)] for k in range(len(w) - n + 1))
    assert clean == {i for i in unique if not dirty(texts[i])}
    copies = {r["doc_id"]: r["copies"] for r in mix(seen[3]).collect()}
    assert mixed == out == {i for i in clean if copies[i]}
    assert kept.count() == sum(copies.values())
    assert corpus_pipeline.run(spark, sf_dir).count() == kept.count()


def test_pipeline_judges_rows_apart_from_their_ids(spark, tmp_path, sf_dir):
    import corpus_pipeline

    from softsplit.llm.mixing import mix

    rng = random.Random(21)
    prose = lambda n: " ".join("".join(rng.choices("abcdefghij", k=5)) for _ in range(n))
    item = spark.read.parquet(f"{sf_dir}/benchmark.parquet").filter("length(text) > 80").first()["text"]
    clean = [prose(60 + i) for i in range(6)]
    copy, other, failing = prose(80), prose(90), "no"

    def table(name, rows):
        given = [(i, t, "en", "s", len(t)) for i, t in rows]
        spark.createDataFrame(given, "doc_id long, text string, lang string, source string, n_chars long").repartition(2).write.parquet(str(tmp_path / name))
        return spark.read.parquet(str(tmp_path / name))

    def texts(df):
        return sorted(r["text"] for r in df.collect())

    docs = table("quality", [(None, failing), (7, failing), (7, clean[0]), *[(None, t) for t in clean[1:]]])
    assert texts(corpus_pipeline.quality(spark, docs, sf_dir)) == sorted(clean)
    docs = table("near", [(None, copy), (None, copy), (None, copy + " end"), (5, other), (5, other), (5, other + " end"), (9, other), (None, other), (None, ""), (None, "")])
    got = corpus_pipeline.near_dedup(spark, docs, sf_dir).collect()
    assert len(got) == 4 and sum(r["text"].startswith(copy) for r in got) == 1
    assert [r["doc_id"] for r in got if r["text"].startswith(other)] == [5]
    docs = table("decontamination", [(None, item), (4, prose(30) + " " + item), (4, clean[0]), *[(None, t) for t in clean[1:]]])
    assert texts(corpus_pipeline.decontaminate(spark, docs, sf_dir)) == sorted(clean)
    docs = table("mixing", [(None if i % 2 else 3, prose(20 + i)) for i in range(40)])
    copies = mix(docs).collect()
    assert len({r["copies"] for r in copies}) > 1
    got = corpus_pipeline.mixing(spark, docs, sf_dir)
    assert got.columns == docs.columns
    assert Counter(r["text"].count(" ") + 1 for r in got.collect()) == Counter({r["size"]: r["copies"] for r in copies if r["copies"]})


def _passes(t):
    ws = WORD.findall(t or "")
    grams = Counter(tuple(ws[j : j + 8]) for j in range(len(ws) - 7))
    hit = {k for j in range(len(ws) - 7) if grams[tuple(ws[j : j + 8])] > 1 for k in range(j, j + 8)}
    return not (len(ws) < 20 or 100 * len(hit) > 30 * len(ws))


def _shingles(t):
    ws = folded(t)
    return {tuple(ws[j : j + 5]) for j in range(len(ws) - 4)} if len(ws) >= 5 else {tuple(ws)}


def _doubled(n):
    """Words of n letters a and b whose sums of powers modulo 2**64 are equal: a doubling word and its complement."""
    one = "".join("ab"[k.bit_count() & 1] for k in range(n))
    return one, one.translate(str.maketrans("ab", "ba"))


@pytest.mark.parametrize("n", [64, 256, 1024, 2048])
def test_words_that_break_sums_of_powers_stay_apart(spark, n):
    import public_tokenizers
    from tokenizers import Tokenizer

    from softsplit.llm.host_rules import host_quality
    from softsplit.llm.maxent import score_texts
    from softsplit.llm.near_dedup import near_components
    from softsplit.llm.suffix_dedup import remove_repeats
    from softsplit.llm.token_shards import token_files

    x, y = _doubled(n)
    tail = " one two three four five six seven"
    rows = [(1, x), (2, y), (3, x + tail + " " + y + tail), (4, x)]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("source", F.lit("s"))
    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    got = _by_id(token_files(df))
    for i, t in rows:
        ids = tok.encode(t, add_special_tokens=False).ids + [0]
        assert got[i]["ids_crc32"] == zlib.crc32(np.array(ids, "<u4").tobytes())
    assert {i: r["component_id"] for i, r in _by_id(near_components(df)).items()} == {1: 1, 2: 2, 3: 3, 4: 1}
    assert {r["n_repeat_words"] for r in host_quality(df).collect()} == {0}
    known = _by_id(score_texts(df, folds=7))
    assert sum(r["n_tokens"] for r in known.values()) == 1 + 1 + 16 + 1 + 4
    left, want = _by_id(remove_repeats(df)), _removed(rows)
    assert {i: r["n_removed"] for i, r in left.items()} == want


def _removed(rows):
    seen, out = set(), {}
    for i, t in rows:
        x = (t or "").encode()
        gone = bytearray(len(x))
        for j in range(len(x) - 99):
            if x[j : j + 100] in seen:
                gone[j : j + 100] = b"\1" * 100
            seen.add(x[j : j + 100])
        out[i] = sum(gone)
    return out


def test_pieces_that_share_a_hash_are_told_by_their_bytes():
    import public_tokenizers

    from softsplit.llm.token_shards import Encoder

    encoder = Encoder(public_tokenizers.path("byte_bpe_50k.json"))
    encoder.hashes = lambda buf, start, end: (end - start).astype(np.uint64) << np.uint64(1)
    texts = ["some words here, others there; some words here", "more words there, and the like of those", "", "a b c d"]
    for _ in range(2):
        ids, sizes = encoder.encode(pa.array(texts))
        want = [encoder.tokenizer.encode(t, add_special_tokens=False).ids + [0] for t in texts]
        assert ids.tolist() == sum(want, []) and sizes.tolist() == [len(w) for w in want]


def test_text_of_very_many_pieces_ends():
    import public_tokenizers

    from softsplit.llm.token_shards import Encoder

    encoder = Encoder(public_tokenizers.path("byte_bpe_50k.json"))
    text = " ".join(f"{i:x}" for i in range(1 << 20, (1 << 20) + 1_200_000))
    ids, sizes = encoder.encode(pa.array([text]))
    assert sizes.tolist() == [len(ids)] and ids[-1] == 0
    assert ids[:200].tolist() == encoder.tokenizer.encode(text[:2000], add_special_tokens=False).ids[:200]


def test_near_dedup_recall_through_all_levels(spark):
    """Pairs just above the threshold, in nodes that branch at every level."""
    from softsplit.llm.near_dedup import near_components

    rng = random.Random(3)
    rows, common = [], [f"shared{k}" for k in range(90)]
    for i in range(150):
        own = [f"own{i}x{k}" for k in range(120)]
        one = common + own
        two = list(one)
        for k in rng.sample(range(90, 210), 5):  # five changed words spoil up to 25 of 206 shingles
            two[k] = f"new{i}x{k}"
        rows += [(2 * i + 1, " ".join(one)), (2 * i + 2, " ".join(two))]
    sets = {i: _shingles(t) for i, t in rows}
    pairs = [(a, a + 1) for a in range(1, 300, 2) if 100 * len(sets[a] & sets[a + 1]) >= 75 * len(sets[a] | sets[a + 1])]
    assert len(pairs) > 100
    assert all(100 * len(sets[a] & sets[b]) < 75 * len(sets[a] | sets[b]) for a in sets for b in sets if a < b and (a, b) not in set(pairs))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = _by_id(near_components(df, node_size=3, depth=3))
    found = sum(got[b]["component_id"] == a for a, b in pairs)
    assert found >= 0.97 * len(pairs)
    assert all(r["component_id"] in (i, i - 1) for i, r in got.items())


def test_near_dedup_chain_in_a_large_cluster(spark):
    """A chain of texts in which only neighbours are linked: rows that are not near the head still meet all others."""
    from softsplit.llm.near_dedup import near_components

    words = [f"w{k}" for k in range(400)]
    rows = [(i + 1, " ".join(words[6 * i : 6 * i + 100])) for i in range(40)]
    sets = {i: _shingles(t) for i, t in rows}
    link = lambda a, b: 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])
    assert link(1, 2) and not link(1, 6)
    df = spark.createDataFrame(rows + [(1000 + i, rows[i][1] + " end") for i in range(40)], "doc_id long, text string")
    got = _by_id(near_components(df, node_size=4, depth=1, cluster_size=8))
    assert {r["component_id"] for r in got.values()} == {1}


def test_maxent_does_not_depend_on_partitions(spark, docs):
    from softsplit.llm.maxent import score_texts

    one = _by_id(score_texts(docs))
    for kw, parts in (({}, 1), ({"frequent": 8}, 7)):
        two = _by_id(score_texts(docs.repartition(parts), **kw))
        for i, r in one.items():
            assert (r["n_known"], r["train_tokens"], r["n_tokens"]) == (two[i]["n_known"], two[i]["train_tokens"], two[i]["n_tokens"])
            assert math.isclose(r["score"], two[i]["score"], rel_tol=1e-9) and math.isclose(r["base_score"], two[i]["base_score"], rel_tol=1e-9)


def test_maxent_score_by_hand(spark, docs, rows):
    """The score of each text, token by token from the trained weights and the counts."""
    from softsplit.llm import maxent

    held = {i: zlib.crc32(str(i).encode()) % 7 == 2 for i, *_ in rows}
    texts = {i: t for i, t, *_ in rows}
    learn = docs.filter(F.col("doc_id").isin([i for i in held if not held[i]])).select("doc_id", "text")
    table = maxent.train(learn)
    bits = 64 - maxent.CLASS_BITS - maxent.GROUP_BITS
    per = {i: maxent.tokens_of(pa.array([t or ""]))[:3] for i, t in texts.items()}
    c = Counter(int(h) for i in texts if not held[i] for h in per[i][0])
    n_group, v_group = Counter(), Counter()
    for h, k in c.items():
        n_group[h >> bits] += k
        v_group[h >> bits] += 1
    softmax = lambda z: np.exp(z - z.max()) / np.exp(z - z.max()).sum()
    got = _by_id(maxent.score_texts(docs))
    for i in list(texts)[:60]:
        want = 0.0
        for h, one, two in zip(*per[i]) if len(per[i][0]) < 400 else ():
            h = int(h)
            cls, group = h >> 59, h >> bits & 31
            kinds, inner = maxent.features(np.array([one]), np.array([two]), np.array([cls]))
            z = table[0].astype(float) + sum(table[k[0]].astype(float) for k in kinds)
            want += math.log10(softmax(z)[cls] * softmax(table[inner[0]].astype(float))[group] * (c[h] + 1) / (n_group[h >> bits] + v_group[h >> bits] + 1))
        assert not want or math.isclose(got[i]["score"], want, rel_tol=1e-4), (i, got[i]["score"], want)


def _best_path(scores, first, step):
    """Plain Viterbi: the best path's labels and its score."""
    best, back = [f + s for f, s in zip(first, scores[0])], []
    for s in scores[1:]:
        ways = [max(range(len(best)), key=lambda j, k=k: best[j] + step[j][k]) for k in range(len(best))]
        best = [best[j] + step[j][k] + s[k] for k, j in enumerate(ways)]
        back.append(ways)
    path = [max(range(len(best)), key=best.__getitem__)]
    for ways in reversed(back):
        path.append(ways[path[-1]])
    return path[::-1], max(best)


def _language_word(model, word):
    """Letters and candidate scores of one word, gram by gram."""
    from softsplit.llm.langid import BUCKETS, ORDERS, RANGES, SCRIPTS

    bits = letters = 0
    for c in word:
        if c.isascii() and c.isalpha() or ord(c) >= 0xAA:
            letters += 1
            bits |= 1 << SCRIPTS.index([s for first, s in RANGES if first <= ord(c)][-1])
    n = len(model.languages)
    total, raw = [0.0] * n, b"\0\0\0 " + word.encode()
    for end in range(4, len(raw)) if letters else ():
        for k, order in enumerate(ORDERS):
            bucket = (int.from_bytes(raw[end + 1 - order : end + 1], "big") * 2654435761 % 2**32 >> 16) + k * BUCKETS
            total = [t + float(w) / len(ORDERS) for t, w in zip(total, model.weights[bucket])]
    fits = [bits & ~int(s) == 0 for s in model.scripts]
    return letters, [t - (1e4 if any(fits) and not f else 0) for t, f in zip(total, fits)]


def test_language_query_against_brute_force_viterbi(spark, sf_dir):
    from softsplit.llm.langid import train
    from softsplit.llm.queries import QUERIES

    rows = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang").collect()
    learn = [(r["text"], r["lang"]) for r in rows if r["lang"] is not None and zlib.crc32(str(r["doc_id"]).encode()) % 5]
    model = train(spark.createDataFrame(learn, "text string, lang string"))
    got = _by_id(QUERIES["op1_language_id"](spark, sf_dir))
    n, known = len(model.languages), {}
    step = [[0 if j == k else -6.0 for k in range(n)] for j in range(n)]
    assert len(got) == len(rows)
    for r in rows:
        words = [w for w in WORD.findall((r["text"] or "").lower())]
        told = [known.get(w) or known.setdefault(w, _language_word(model, w)) for w in words]
        mass = [0] * n
        if told:
            for (letters, _), k in zip(told, _best_path([s for _, s in told], [0.0] * n, step)[0]):
                mass[k] += letters
        have = got[r["doc_id"]]
        if not any(map(str.isalpha, r["text"] or "")):
            assert (have["lang_pred"], have["score"]) == ("und", 0)
        else:
            assert have["lang_pred"] == model.languages[max(range(n), key=mass.__getitem__)], r["doc_id"]
            assert abs(have["score"] - max(mass) / sum(mass)) < 1e-9, r["doc_id"]


def _turn_codes(text, first):
    from softsplit.llm.chat import _MARK, LEVELS, MARKERS

    text = text or ""
    found = re.match(_MARK, text)
    word = found.group(1).lower() if found else ""
    marker = max([k for k, names in enumerate(MARKERS.values(), 1) if word in names], default=0)
    end = {"?": 1, ".": 2, ":": 3}.get(text.rstrip(" ")[-1:], 0)
    listed = re.search(r"(?m)^\s*(?:[-*]|\d+[.)]|```)", text) is not None
    return [marker, min(int(math.log2(len(text) + 1)), LEVELS - 1), min(text.count("\n") + 1, 4), end, int(first), int(listed)]


def test_chat_query_against_brute_force_viterbi(spark, sf_dir):
    from softsplit.llm.chat import FEATURES, LEVELS
    from softsplit.llm.queries import QUERIES

    talks = defaultdict(list)
    for r in spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text").collect():
        talks[r["conv_id"]].append((r["turn"], r["role"], r["text"]))
    roles = sorted({role for t in talks.values() for _, role, _ in t if role is not None})
    n, starts, steps, emits, codes = len(roles), Counter(), Counter(), Counter(), {}
    for conv, turns in talks.items():
        turns.sort(key=lambda t: t[0])
        codes[conv] = [_turn_codes(text, turn == turns[0][0]) for turn, _, text in turns]
        if zlib.crc32(str(conv).encode()) % 5 == 0:
            continue
        for i, ((turn, role, _), code) in enumerate(zip(turns, codes[conv])):
            starts[role] += code[FEATURES.index("first")]
            emits.update((f, level, role) for f, level in enumerate(code))
            if i and turns[i - 1][0] == turn - 1:
                steps[turns[i - 1][1], role] += 1

    def logs(counts):
        return [math.log((c + 1) / (sum(counts) + len(counts))) for c in counts]

    start, step = logs([starts[r] for r in roles]), [logs([steps[a, b] for b in roles]) for a in roles]
    emit = {(f, r): logs([emits[f, level, r] for level in range(LEVELS)]) for f in range(len(FEATURES)) for r in roles}
    got = defaultdict(list)
    for r in QUERIES["op4_chat_format"](spark, sf_dir).collect():
        got[r["conv_id"]].append((r["turn"], r["role_pred"]))
    assert {c: len(t) for c, t in got.items()} == {c: len(t) for c, t in talks.items()}
    for conv, turns in talks.items():
        scores = [[sum(emit[f, r][level] for f, level in enumerate(code)) for r in roles] for code in codes[conv]]
        path = [roles.index(p) for _, p in sorted(got[conv])]
        value = start[path[0]] + sum(s[k] for s, k in zip(scores, path)) + sum(step[a][b] for a, b in zip(path, path[1:]))
        assert abs(value - _best_path(scores, start, step)[1]) < 1e-6, conv


def test_chat_repeated_turns_do_not_depend_on_partitions(spark):
    from softsplit.llm.chat import format_chats

    rng = random.Random(3)
    texts = ["User: hi?", "Assistant: it is.", "a longer line with more words in it.", "- one\n- two", ""]
    rows = [(c, rng.randrange(4), rng.choice(["user", "assistant"]), rng.choice(texts)) for c in range(12) for _ in range(20)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    one, two = (Counter(map(tuple, format_chats(d).collect())) for d in (df.coalesce(1), df.orderBy(F.rand(1)).repartition(7)))
    assert one == two and sum(one.values()) == len(rows)


def test_transcripts_are_parsed_into_turns(spark, sf_dir):
    """Turns marked by a speaker word on their first line, and the same turns unmarked: there only lengths and order tell."""
    from softsplit.llm.chat import MARKERS, RoleModel, fit_lines, parse_transcripts

    rng = random.Random(4)
    plain = [tuple(r) for r in spark.read.parquet(f"{sf_dir}/../sf0.01/conversations.parquet").select("conv_id", "turn", "role", "text").collect()]
    marked = [(c, t, role, f"{rng.choice(MARKERS[role]).title()}: {text or ''}") for c, t, role, text in plain]
    shares = {}
    for name, rows in (("plain", plain), ("marked", marked)):
        held = defaultdict(list)
        for r in sorted(rows):
            if zlib.crc32(str(r[0]).encode()) % 5 == 0:
                held[r[0]].append(r)
        model = fit_lines(spark.createDataFrame([r for r in rows if r[0] not in held], "conv_id long, turn long, role string, text string"))
        raw = spark.createDataFrame([(c, "\n".join(x[3] or "" for x in t)) for c, t in held.items()], "id long, text string")
        got = defaultdict(list)
        for r in parse_transcripts(raw, model).collect():
            got[r["conv_id"]].append((r["turn"], r["role_pred"], r["text"]))
        said, true = [], []
        for c, turns in held.items():
            mine = sorted(got[c])
            assert [t for t, *_ in mine] == list(range(len(mine)))
            said += [(role, line) for _, role, text in mine for line in text.split("\n") if line.strip(" ")]
            true += [(role, line) for *_, role, text in turns for line in (text or "").split("\n") if line.strip(" ")]
        assert [line for _, line in said] == [line for _, line in true]
        shares[name] = sum(a == b for a, b in zip(said, true)) / len(true)
    print(shares, max(Counter(role for role, _ in true).values()) / len(true))
    assert shares["marked"] >= 0.95
    assert shares["plain"] > max(Counter(role for role, _ in true).values()) / len(true)
    odd = [(None, "User: hi\n\nthere\nAssistant: ok"), (None, None), (1, ""), (1, " \n "), (1, "x"), (1, "x")]
    odd = spark.createDataFrame([(*o, 3) for o in odd], "id long, text string, code int")
    assert Counter(r["conv_id"] for r in parse_transcripts(odd, model).filter("turn = 0").collect()) == {None: 1, 1: 2}
    assert parse_transcripts(odd.limit(0), model).count() == 0
    bare = RoleModel([], np.zeros(1), np.zeros((1, 1)), np.zeros((6, 16, 1)))
    assert {(r["role_pred"], r["turn"]) for r in parse_transcripts(odd, bare).collect()} == {(None, 0)}
