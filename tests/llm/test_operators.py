"""Each corpus operator against brute force, an exact round trip or held-out labels, and on odd tables."""

import hashlib
import re
import time
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
import xxhash
from tokenizers import Tokenizer

from dense_tucker.llm import bpe, common, decontam, html_tree, langid, lexing, lm_scoring, packing, pii, quality_crf, quality_rules, queries, simhash, token_store

BYTE, WORD = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("word_bpe_49k.json")
ODD = ["", None, " ", "a", "\n\n", "it's  'so\tx ", "é́ x ß, ﷺ 日本 語", "<|endoftext|> a <| b", "A b c d e f\nA b c d e f\n", "+1 (555) 123-4567 a.b@c.de 1.2.3.4", "x " * 3000, "a,b.c!? d:e;", " lead", "trail ", "a\r\nb\x0bc\x1cd", " nb　x"]


@pytest.fixture(scope="module")
def docs(spark, small):
    return spark.read.parquet(f"{small}/documents.parquet").persist()


@pytest.fixture(scope="module")
def labels(spark, small):
    return spark.read.parquet(f"{small}/labels.parquet")


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(i, t, "en" if i % 2 else None, None, None, 0.5, 1, 7) for i, t in enumerate(ODD)] + [(3, "a", "en", "s", 1, 0.1, 1, 7), (None, "no id here", "fr", None, 5, 0.2, 0, 8)]
    return spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint, score double, predicted int, fp bigint")


@pytest.fixture(scope="module")
def empty(odd):
    return odd.where("false")


def texts(df):
    return {r["doc_id"]: r["text"] or "" for r in df.select("doc_id", "text").collect()}


def test_word_hashes_tell_words_apart():
    words = [b"a", b"b", b"ab", b"ba", b"aa", b"a" * 9]
    assert len({lexing.hash_word(w) for w in words}) == len(words)
    data = np.frombuffer(b" a ab\ta", np.uint8)
    h, _, _, row = lexing.words(data, np.array([0]), np.array([len(data)]))
    assert h.tolist() == [lexing.hash_word(b"a"), lexing.hash_word(b"ab"), lexing.hash_word(b"a")] and row.tolist() == [0, 0, 0]


@pytest.mark.parametrize("path", [BYTE, WORD])
def test_piecewise_ids_equal_the_library(docs, path):
    import pyarrow as pa

    coder, library = bpe.Encoder(path, cache=200), Tokenizer.from_file(path)
    sample = [t for t in texts(docs).values()][:60] + ODD
    for _ in range(2):  # a small cache is cleared in between
        data, a, b = common.texts_of(pa.array(sample))
        ids, n = coder.encode_bytes(data, a, b)
        for text, got in zip(sample, np.split(ids, np.cumsum(n)[:-1]), strict=True):
            assert got.tolist() == library.encode(text or "", add_special_tokens=False).ids


def test_quality_rules_counts(docs, labels, odd):
    def brute(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", t)
        c = Counter(zip(w, w[1:], w[2:], strict=False))
        rep = {k for i in range(len(w) - 2) if c[tuple(w[i : i + 3])] > 1 for k in (i, i + 1, i + 2)}
        seen, dup = set(), 0
        for line in t.split("\n"):
            if re.search(r"[^\x20\x09-\x0D]", line):
                dup += line in seen
                seen.add(line)
        return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), dup, len(rep)

    trusted = labels.where("quality = 1")
    for df in (docs, odd.where("doc_id is not null").dropDuplicates(["doc_id"])):
        own = texts(df)
        for r in quality_rules.apply(df, trusted).collect():
            want = brute(own[r["doc_id"]])
            assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == want
            assert r["base_failed"] == (want[0] < 50 or 100 * want[4] > 50 * want[0])
            assert not (r["base_failed"] and r["kept"])


def test_simhash_against_all_pairs(docs, odd):
    def mark(t):
        w = t.encode().lower().split()
        shingles = [b" ".join(w[i : i + 4]) for i in range(max(1, len(w) - 3))] if w else []
        h = [xxhash.xxh64_intdigest(x, 42) for x in shingles]
        return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))

    own = texts(docs)
    got = {r["doc_id"]: r for r in simhash.cluster(docs).collect()}
    marks = {k: mark(t) for k, t in own.items()}
    assert all(int(got[k]["fingerprint"], 16) == v and len(got[k]["fingerprint"]) == 16 for k, v in marks.items())
    assert {k: r["component_id"] for k, r in got.items()} == components(marks)
    assert simhash.cluster(odd).count() == len(ODD) + 2


def components(marks):
    up = {k: k for k in marks}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    keys = sorted(marks)
    for i, a in enumerate(keys):
        for b in keys[i + 1 :]:
            if (marks[a] ^ marks[b]).bit_count() <= 4:
                x, y = sorted((find(a), find(b)))
                up[y] = x
    return {k: find(k) for k in keys}


@pytest.mark.parametrize("hot", [2, 4000])
def test_links_of_dense_fingerprints(spark, hot):
    """Near fingerprints, chains and hot buckets: components equal those of all pairs."""
    rng = np.random.default_rng(3)
    values = []
    for _ in range(6):
        x = int(rng.integers(0, 1 << 63))
        for _ in range(25):
            for b in rng.integers(0, 64, rng.integers(0, 6)):
                x ^= 1 << int(b)
            values.append(x & ((1 << 64) - 1))
    marks = {i: v for i, v in enumerate(dict.fromkeys(values))}
    signed = {i: v - (1 << 64) if v >> 63 else v for i, v in marks.items()}
    df = spark.createDataFrame([(v,) for v in signed.values()], "fp bigint")
    roots = {r["node"]: r["root"] for r in simhash.components(simhash.links(df, hot_rows=hot)).collect()}
    want = components(marks)
    got = {i: roots.get(v, v) for i, v in signed.items()}
    groups = lambda m: sorted(sorted(k for k in m if m[k] == x) for x in set(m.values()))
    assert groups(got) == groups(want)


def test_decontamination_equals_brute_force(spark, docs, odd, small):
    bench = spark.read.parquet(f"{small}/benchmark.parquet").select("item_id", "text")
    more = spark.createDataFrame([(900, "a"), (901, None), (902, "..."), (903, "no ID")], "item_id bigint, text string")
    bench = bench.union(more)
    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    low = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    windows = {}
    for r in bench.collect():
        w = word.findall((r["text"] or "").translate(low))
        for i in range(max(1, len(w) - 9) if w else 0):
            windows.setdefault(tuple(w[i : i + 10]), set()).add(str(r["item_id"]))
    for df in (docs, odd.where("doc_id is not null").dropDuplicates(["doc_id"])):
        own = texts(df)
        for r in decontam.apply(df, bench).collect():
            w = word.findall(own[r["doc_id"]].translate(low))
            hit, items = set(), set()
            for n in {len(x) for x in windows}:
                for i in range(len(w) - n + 1):
                    if tuple(w[i : i + n]) in windows:
                        hit |= set(range(i, i + n))
                        items |= windows[tuple(w[i : i + n])]
            assert (r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"], r["contaminated"]) == (len(w), len(hit), len(items), hashlib.sha256(",".join(sorted(items)).encode()).hexdigest(), bool(hit))
    kept = decontam.keep_clean(odd, bench)
    assert kept.columns == odd.columns and {r["text"] for r in kept.collect()} & {"a", "no id here"} == set()


def test_proximity(spark):
    df = spark.createDataFrame([(1, "red x x blue"), (2, "blue red"), (3, "red x x x x blue"), (4, None), (5, "x"), (6, "red")], "doc_id bigint, text string")
    got = {r["doc_id"]: r["near_ids"] for r in decontam.search(decontam.build_index(df), [decontam.Phrases.of([("i", "red blue")])], reach=3).collect()}
    assert got == {1: ["i"], 2: ["i"], 3: [], 4: [], 5: [], 6: []}


def test_one_index_for_any_test_set(spark, docs, small, tmp_path):
    """The index is built without a test set; slices of a test set give the same answers as all of it at once."""
    bench = spark.read.parquet(f"{small}/benchmark.parquet")
    index = decontam.write_index(docs, str(tmp_path / "index"))
    spelled = index.select("spelled", "spelled_ends").first()
    assert len(np.frombuffer(spelled["spelled_ends"], np.int32)) > 1_000
    whole = sorted(decontam.search(index, decontam.phrases_of(bench)).collect(), key=lambda r: r["doc_id"])
    cut = list(decontam.phrases_of(bench, slice_bytes=2_000))
    assert len(cut) > 3
    assert sorted(decontam.search(index, cut).collect(), key=lambda r: r["doc_id"]) == whole
    other = decontam.Phrases.of([("own", texts(docs)[whole[0]["doc_id"]])])
    assert whole[0]["doc_id"] in {r["doc_id"] for r in decontam.search(index, [other]).where("contaminated").collect()}


def test_decontamination_query_equals_sql(spark, small):
    import duckdb

    db = duckdb.connect()
    for name in ("documents", "benchmark"):
        db.execute(f"create view {name} as select * from read_parquet('{small}/{name}.parquet')")
    got = queries.op6_positional_index(spark, small)
    want = db.execute(queries.OP6_SQL).fetchall()
    names = [x[0] for x in db.description]
    assert sorted(names) == sorted(got.columns)
    assert sorted(map(tuple, got.select(*names).collect())) == sorted(want) and sum(r[names.index("n_near")] for r in want) > 0


def same_length_twins(n):
    """Two unlike texts of n characters whose polynomial hashes modulo 2**64 are equal."""
    signs = [bin(i).count("1") & 1 for i in range(n)]
    return "".join("ab"[s] for s in signs), "".join("ba"[s] for s in signs)


def test_unlike_texts_with_like_structure(spark):
    for n in (1024, 2048, 4096):
        a, b = same_length_twins(n)
        assert lexing.hash_word(a.encode()) != lexing.hash_word(b.encode())
        df = spark.createDataFrame([(1, a), (2, b), (3, f"{a}\n{b}\n{a}")], "doc_id bigint, text string")
        for path in (BYTE, WORD):
            library = Tokenizer.from_file(path)
            want = {r: zlib.crc32(np.asarray(library.encode(t, add_special_tokens=False).ids + [1], "<u4").tobytes()) for r, t in ((1, a), (2, b))}
            assert want.items() <= {r["doc_id"]: r["ids_crc32"] for r in token_store.write_store(df, path).records().collect()}.items()
        counts = {r["doc_id"]: r["n_dup_lines"] for r in quality_rules.apply(df, df.where("doc_id = 1")).collect()}
        assert counts == {1: 0, 2: 0, 3: 1}
        bench = spark.createDataFrame([("x", a)], "item_id string, text string")
        assert {r["doc_id"]: r["contaminated"] for r in decontam.apply(df, bench).collect()} == {1: True, 2: False, 3: True}


def test_answers_do_not_rest_on_hashes(docs, labels, spark, small, monkeypatch):
    """With a hash of few values, all exact answers stay."""
    import pyarrow as pa

    sample = [t for t in texts(docs).values()][:25] + ODD
    data, a, b = common.texts_of(pa.array(sample))
    plain = quality_rules.base_counts(data, a, b)
    real = lexing.span_hashes
    monkeypatch.setattr(lexing, "span_hashes", lambda d, s, e: real(d, s, e) % np.uint64(97) + np.uint64(1))
    poor = quality_rules.base_counts(data, a, b)
    assert all((plain[k] == poor[k]).all() for k in plain if k[0] != "_")
    for path in (BYTE, WORD):
        coder = bpe.Encoder(path)
        ids, n = coder.encode_bytes(data, a, b)
        for text, got in zip(sample, np.split(ids, np.cumsum(n)[:-1]), strict=True):
            assert got.tolist() == coder.library.encode(text or "", add_special_tokens=False).ids


def test_session_settings_stay(spark, docs, labels, small):
    keys = ("spark.sql.execution.arrow.maxRecordsPerBatch", "spark.sql.execution.arrow.maxBytesPerBatch")
    before = [spark.conf.get(k, None) for k in keys]
    bench = spark.read.parquet(f"{small}/benchmark.parquet")
    decontam.apply(docs, bench).count()
    lm_scoring.apply(docs, labels.where("quality = 1")).count()
    token_store.write_store(docs, WORD).records().count()
    assert [spark.conf.get(k, None) for k in keys] == before


def test_near_duplicates_keep_unlike_texts(spark):
    words = [f"w{i}" for i in range(300)]
    rows = [(1, "one two three four five"), (1, "some quite other words here"), (2, "and a third text of words"), (3, " ".join(words)), (4, " ".join(words)), (None, " ".join(words)), (None, "no id but text of its own"), (7, "same row"), (7, "same row"), (8, None), (9, "")]
    df = spark.createDataFrame([(*r, "x") for r in rows], "doc_id bigint, text string, source string")
    kept = sorted(((r["doc_id"], r["text"]) for r in simhash.keep_one(df).collect()), key=str)
    assert kept == sorted([(1, "one two three four five"), (1, "some quite other words here"), (2, "and a third text of words"), (3, " ".join(words)), (None, "no id but text of its own"), (7, "same row"), (8, None)], key=str)


def test_packing(docs, odd):
    library = Tokenizer.from_file(BYTE)
    for df in (docs, odd):
        rows = packing.pack(df, BYTE, with_ids=True).orderBy("sequence_id", "offset").collect()
        place = 0
        for r in rows:
            assert r["sequence_id"] * 2048 + r["offset"] == place
            assert r["ids_crc32"] == zlib.crc32(r["ids"]) and len(r["ids"]) == 4 * r["length"]
            place += r["length"]
        if df is docs:
            parts = {}
            for r in sorted(rows, key=lambda r: r["start"]):
                parts.setdefault(r["doc_id"], []).extend(np.frombuffer(r["ids"], "<u4").tolist())
            for k, t in list(texts(docs).items())[:50]:
                assert parts[k] == library.encode(t, add_special_tokens=False).ids + [1]


def test_token_store_round_trip(docs, odd, spark):
    library = Tokenizer.from_file(WORD)
    store = token_store.write_store(docs, WORD, shard_bytes=4_000)
    own = texts(docs)
    rows = sorted(store.records(with_ids=True).collect(), key=lambda r: r["start"])
    at = 0
    for r in rows:
        want = np.asarray(library.encode(own[r["doc_id"]], add_special_tokens=False).ids + [1], "<u4").tobytes()
        assert (r["start"], r["n_tokens"], r["ids_crc32"], r["ids"]) == (at, len(want) // 4, zlib.crc32(want), want)
        at += r["n_tokens"]
    assert [r["doc_id"] for r in rows] == sorted(own)
    keys = sorted(own)[3:60:7]
    found = {r["doc_id"]: r["ids"] for r in store.lookup([*keys, 10**9, -5]).collect()}
    assert found == {r["doc_id"]: r["ids"] for r in rows if r["doc_id"] in keys}
    again = token_store.write_store(odd, WORD).records().collect()
    assert len(again) == len(ODD) + 2 and sum(r["doc_id"] is None for r in again) == 1
    starts = sorted((r["start"], r["n_tokens"]) for r in again)
    assert all(a + n == b for (a, n), (b, _) in zip(starts, starts[1:], strict=False))


def test_perfect_hash():
    keys = np.unique(np.random.default_rng(0).integers(-(1 << 62), 1 << 62, 5000))
    index = token_store.build_index(keys)
    assert sorted(token_store.find_slots(keys, *index).tolist()) == list(range(len(keys)))
    for n in (1, 10, 100):
        probes: list[int] = []
        token_store.find_slots(keys[:n], *index, probes)
        assert n <= sum(probes) <= 6 * n + 8  # bits looked at: by the keys asked for, not by the index


def test_hot_keys_are_split(spark):
    rows = [(7, f"text number {i} " + "word " * 50) for i in range(300)] + [(None, f"none {i} " + "word " * 50) for i in range(200)] + [(i, f"doc {i}") for i in range(100)]
    store = token_store.write_store(spark.createDataFrame(rows, "doc_id bigint, text string"), WORD, shard_bytes=2_000, parts=8)
    got = store.records().collect()
    assert len(got) == 600 and [sum(r["doc_id"] == k for r in got) for k in (7, None)] == [301, 200]
    own = store.directory().where("first_key = 7 and last_key = 7 and n_docs > 1").collect()
    assert len({r["part"] for r in own}) > 1 and max(r["n_ids"] for r in own) < 3_000
    ordered = sorted(got, key=lambda r: r["start"])
    at = 0
    for r in ordered:
        assert r["start"] == at
        at += r["n_tokens"]
    keys = [-1 if r["doc_id"] is None else r["doc_id"] for r in ordered]
    assert keys == sorted(keys)
    pieces = store.lookup([7, 50, 1_000]).collect()
    assert sum(r["n_tokens"] for r in pieces if r["doc_id"] == 7) == sum(r["n_tokens"] for r in got if r["doc_id"] == 7) and sum(r["doc_id"] == 50 for r in pieces) == 1


def plain_spans(t):
    """Base spans by the patterns themselves."""
    out = [("email", *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    out += [("ip", *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(x) <= 255 for x in m[0].split("."))]
    for kind, pattern, low, high in (("card", r"[0-9]([\x20-]?[0-9])+", 12, 19), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", 9, 15)):
        for m in re.finditer(pattern, t):
            digits = [int(c) for c in m[0] if c.isdigit()]
            sums = sum(d if i % 2 == 0 else sum(divmod(2 * d, 10)) for i, d in enumerate(digits[::-1]))
            if low <= len(digits) <= high and (kind == "phone" or sums % 10 == 0):
                out.append((kind, *m.span()))
    order = ["email", "ip", "card", "phone"]
    return ",".join(f"{k}:{a}:{b}" for k, a, b in sorted(out, key=lambda s: (s[1], order.index(s[0]))))


def test_personal_data(docs, odd):
    assert plain_spans("a.b@c.de 1.2.3.400 x +1 (555) 123-4567 x 4111 1111 1111 1111 x 1.2.3.4") == "email:0:8,phone:21:38,card:41:60,ip:63:70"
    net = pii.train(docs)
    for df in (docs, odd):
        own = texts(df)
        for r in pii.find(df, net).collect():
            if r["doc_id"] in own and r["doc_id"] not in (None, 3):
                base = plain_spans(own[r["doc_id"]])
                assert r["base_sha256"] == hashlib.sha256(base.encode()).hexdigest()
                assert [r[f"n_{k}"] for k in pii.KINDS] == [base.count(k) for k in pii.KINDS]
                every = list(filter(None, r["spans"].split(",")))
                assert set(filter(None, base.split(","))) <= set(every) and len(every) == r["n_spans"] == r["n_added"] + len(list(filter(None, base.split(","))))
    clean = {r["doc_id"]: r["text"] for r in pii.redact(docs, docs).collect()}
    assert all(not plain_spans(t or "") for t in clean.values())
    out = pii.redact(odd, docs)
    assert out.columns == odd.columns and out.count() == odd.count()


def test_personal_data_patterns():
    """The linear scanners equal the patterns on random texts, and long runs end at once."""
    rng = np.random.default_rng(1)
    for k in range(6_000):
        letters = list(("a@.", "a@.-1 ", "12.", "0123456789.", "+1(). -5", "a1@.+%- ")[k % 6])
        text = "".join(rng.choice(letters, int(rng.integers(0, 40))))
        assert pii.written(pii.base_spans(text)) == plain_spans(text), text
    began = time.perf_counter()
    assert pii.base_spans("1" * 5_000 + ".1.1.1") == []
    for text in ("1" * 500_000, "a" * 500_000 + "@", "a@" * 200_000, "1." * 200_000, "+1 " * 200_000, "+1" + " " * 500_000, "." * 500_000 + "@a", "1 " * 300_000):
        pii.base_spans(text)
    assert time.perf_counter() - began < 20


def test_personal_data_in_other_writings(spark):
    """Held-out texts and values in writings that the base patterns do not find; clean texts stay alone."""
    rows = [r["text"] for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").orderBy("doc_id").select("text").collect()]
    net = pii.fit(rows[:700])
    samples = pii.disguised_samples(rows[700:], 1_500, seed=99)
    found = pii.all_spans([t for t, _, _ in samples], net)
    hidden = sum(len(x) for _, _, x in samples)
    hit = sum(len(set(x) & set(every)) for (_, _, x), (_, every) in zip(samples, found, strict=True))
    added = sum(len(every) - len(own) for own, every in found)
    assert hidden > 500 and hit >= 0.9 * hidden and hit >= 0.97 * added
    clean = [re.sub("[0-9@]", "", t) for t in rows[700:]]
    long = next(t for t in clean if len(t) > 2_000)
    put = [long[:1_500] + f" {v} " + long[1_500:] for v in ("jo.smith (at) mail (dot) org", "ann[at]host[dot]com", "plus four nine three zero one two three four five six seven")]  # nothing that a base pattern needs
    assert sum((1501 == s[1]) for _, every in pii.all_spans(put, net) for s in every) >= 2
    assert sum(bool(every) for _, every in pii.all_spans(clean, net)) <= 0.005 * len(clean)


def test_personal_data_windows():
    for n in (0, 1, 63, 64, 767, 768, 769, 1_472, 1_473, 5_000):
        parts = pii.windows_of(n)
        assert [k for _, _, a, b in parts for k in range(a, b)] == list(range(n))
        assert all(f <= a and b <= e and e - f <= pii.WINDOW for f, e, a, b in parts)
    rng = np.random.default_rng(0)
    net = pii.Tagger.new()
    codes = rng.integers(1, 98, (5, 64))
    assert np.allclose(net.scores(codes.astype(np.uint8)).transpose(0, 2, 1), net.emissions(codes)[0], atol=1e-5)
    scores = rng.normal(0, 2, (64, 9, 40)).astype(np.float32)
    scores[:, 0] += rng.uniform(0, 8, 40).astype(np.float32)
    net.p["move"] = rng.normal(0, 1, (9, 9)).astype(np.float32)
    best = net.decode(scores.transpose(0, 2, 1), np.ones((64, 40), bool))
    assert np.flatnonzero(best.any(1)).tolist() == net.undecided(scores).tolist()


def test_personal_data_scores_saturate_and_padding_is_masked_once():
    rng = np.random.default_rng(1)
    net = pii.Tagger.new()
    net.p["b"] += rng.normal(0, 300, net.p["b"].shape).astype(np.float32)  # exponentials overflow
    codes = rng.integers(1, 98, (7, 33))
    with np.errstate(all="raise", under="ignore"):
        got = net.scores(codes.astype(np.uint8))
    assert np.isfinite(got).all() and np.allclose(got.transpose(0, 2, 1), net.emissions(codes)[0], atol=1e-5)
    scores = rng.normal(0, 2, (33, 9, 40)).astype(np.float32)
    scores[:, 0] += rng.uniform(0, 8, 40).astype(np.float32)
    mask = np.arange(33)[:, None] < rng.integers(1, 34, 40)
    away = scores.copy()
    away[:, 1:] -= np.where(mask, np.float32(0), np.float32(1e4))[:, None]
    assert net.undecided(scores, mask).tolist() == net.undecided(away).tolist()


def test_personal_data_borders_are_tried_only_where_a_value_may_lie(monkeypatch):
    """Stretches of words that hold no value cost no check, whatever the network found there; values between them are found as before."""
    checked = []
    plainly = pii.plainly
    monkeypatch.setattr(pii, "plainly", lambda kind, value: checked.append(value) or plainly(kind, value))
    words = " ".join(["lorem", "that", "ipsum."] * 20)
    for kind in pii.KINDS:
        assert pii._snapped(words, kind, 100, 160) is None
    assert not checked
    for kind, value in (("email", "jo.smith (at) mail (dot) org"), ("email", "ann [ at ] host dot com"), ("ip", "192 . 0 . 2 . 7"), ("card", "4111.1111.1111.1111"), ("phone", "plus four nine three zero one two three four five six seven"), ("phone", "(555) 123-4567")):
        text = f"{words} {value} {words}"
        at = len(words) + 1
        for a, b in ((at, at + len(value)), (at + 6, at + len(value) - 3), (at - 9, at + len(value))):
            assert pii._snapped(text, kind, a, b) == (kind, at, at + len(value)), (kind, value, a, b)
    assert len(checked) < 300
    odd = "one \u017fix two three four five six seven eight nine zero"
    assert pii._snapped(odd, "phone", 0, len(odd)) == ("phone", 8, len(odd))  # a letter that folds to s spells no digit


def test_personal_data_gradients():
    rng = np.random.default_rng(0)
    net = pii.Tagger.new(hidden=3, embed=2)
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    codes, tags = rng.integers(1, 98, (2, 6)), rng.integers(0, 9, (2, 6))
    tags[1, 4:] = -1
    codes[1, 4:] = 0

    def value():
        scores, _ = net.emissions(codes)
        total = 0.0
        for b in range(2):
            n = int((tags[b] >= 0).sum())
            e, move = scores[:n, b].astype(float), net.p["move"]
            a = e[0]
            for t in range(1, n):
                a = np.logaddexp.reduce(a[:, None] + move, axis=0) + e[t]
            total += sum(e[t, tags[b, t]] for t in range(n)) + sum(move[tags[b, t - 1], tags[b, t]] for t in range(1, n)) - np.logaddexp.reduce(a)
        return total / 2

    grads = net.gradients(codes, tags)
    places = {"move": [(1, 2)], "out": [(0, 1, 2), (1, 2, 0)], "w": [(0, 1, 2), (1, 4, 9), (0, 3, 11)], "b": [(1, 4)], "out_b": [(3,)], "embed": [(int(codes[0, 0]), 0), (0, 1)]}
    for name, at in ((k, x) for k, xs in places.items() for x in xs):
        keep = net.p[name][at]
        net.p[name][at] = keep + 1e-4
        up = value()
        net.p[name][at] = keep - 1e-4
        slope = (up - value()) / 2e-4
        net.p[name][at] = keep
        assert slope == pytest.approx(grads[name][at], abs=1e-5)


def test_line_field_marginals():
    rng = np.random.default_rng(0)
    field = quality_crf.Field(np.zeros(1), rng.normal(size=(2, 2)), 0.0)
    good, n = rng.normal(size=9), np.array([3, 0, 5, 1])
    p, _, log_z = field.marginals(good, np.cumsum(n) - n, n)
    for first, size in zip(np.cumsum(n) - n, n, strict=True):
        total, ones = 0.0, np.zeros(size)
        for state in range(2**size):
            y = [state >> t & 1 for t in range(size)]
            w = np.exp(sum(good[first + t] for t in range(size) if y[t]) + sum(field.moves[y[t - 1], y[t]] for t in range(1, size)))
            total += w
            ones += w * np.array(y)
        if size:
            assert np.allclose(p[first : first + size], ones / total)
            assert np.isclose(log_z[first : first + size].sum(), np.log(total))


def test_quality_on_held_out_labels(spark):
    sf = "/root/testdata/sf0.01"
    rows = queries.op1_quality_crf(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out").collect()
    assert sum(r["predicted"] == r["quality"] for r in rows) >= 0.95 * len(rows)


def test_language_on_held_out_rows(spark):
    sf = "/root/testdata/sf0.01"
    own = {r["doc_id"]: r["lang"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    rows = [r for r in queries.op5_language_codes(spark, sf).collect() if r["held_out"]]
    assert sum(r["lang_pred"] == own[r["doc_id"]] for r in rows) >= 0.98 * len(rows)
    for n in (2, 4, 7, 12):
        code = langid.codewords(n)
        apart = min(int((code[i] != code[j]).sum()) for i in range(n) for j in range(i))
        assert apart >= (code.shape[1] + 1) // 2 if n <= 7 else apart > 5


def test_style_tree(spark):
    page = "<html><body><nav><ul><li>Home</li></ul></nav><div class='ad'>Buy</div><article><h1>T &amp; t</h1><p><b>One {0}<br>two<p>Three {0}<div class=comments>No</div></article><footer>f {0}</footer>"
    free = "<body><div><p>Shared line</p></div><section><p>Own text {0}</p></section></body>"
    rows = [(i, f"http://h.x/{i}", page.format(i)) for i in range(5)] + [(100 + i, f"http://free.x/{i}", free.format(i)) for i in range(200)] + [(999, None, None), (998, "u", "")]
    df = spark.createDataFrame(rows, "page_id bigint, url string, html string")
    got = {r["page_id"]: r for r in html_tree.extract(df).collect()}
    assert got[2]["text"] == "T & t\nOne 2 two\nThree 2" and got[2]["n_chars"] == 23
    assert got[150]["text"] == "Own text 50" and got[999]["text"] == got[998]["text"] == ""


def test_style_tree_keeps_copies(spark):
    """Articles that recur on a host, whole or under new titles, keep their text; recurring lines beside varying text go."""
    article = "<body><article><h1>{1}</h1>" + "".join(f"<p>Paragraph {i} of article {{0}}.</p>" for i in range(10)) + "</article>"
    line = "<body><article><div><p>Shared line</p></div><section><p>Own long text {0} of page {0}</p></section></article>"
    rows = [(i, f"http://one.x/{i}", article.format(0, "T")) for i in range(300)] + [(1000 + i, f"http://some.x/{i}", article.format(i % 20, "T")) for i in range(300)]
    rows += [(2000 + i, f"http://title.x/{i}", article.format(0, f"T {i}")) for i in range(300)] + [(3000 + i, f"http://line.x/{i}", line.format(i)) for i in range(300)]
    got = {r["page_id"]: r["text"].split("\n") for r in html_tree.extract(spark.createDataFrame(rows, "page_id bigint, url string, html string")).collect()}
    assert all(sum(x.startswith("Paragraph") for x in got[i]) == 10 for i in got if i < 3000)
    assert all(got[3000 + i] == [f"Own long text {i} of page {i}"] for i in range(300))


def test_style_tree_sees_past_names(spark):
    """Wrappers with noise-like names and titles with main-like ones do not hide a page's text; named noise beside text stays out."""
    forms = ["<body><div class='layout has-sidebar'><article><p>Body {0}</p></article></div>", "<body><div id='page' class='no-comments'><div><p>Body {0}</p></div></div>", "<body><div class='sidebar layout'><main><p>Body {0}</p></main></div>", "<body><div class='content'><h1 class='entry-title'>T {0}</h1><p>Body {0}</p><p>Other {0} words</p></div>", "<body><div class='widget'><p>Body {0}</p></div>", "<body><article><p>Main {0}</p></article><div class='x'><p>Body {0}</p></div>", "<body><article><p>Main {0}</p></article><div class='ad'>Body {0}</div><footer>f {0}</footer>"]
    rows = [(1000 * k + i, f"http://h{k}.x/{i}", form.format(i)) for k, form in enumerate(forms) for i in range(100)]
    got = {r["page_id"]: r["text"].split("\n") for r in html_tree.extract(spark.createDataFrame(rows, "page_id bigint, url string, html string")).collect()}
    for k in range(len(forms)):
        assert all((f"Body {i}" in got[1000 * k + i]) == (k < 6) for i in range(100)), k
    assert got[6005] == ["Main 5"]


def article_text(page):
    """What a reader sees of the given pages' article: blocks of the article element, one a line."""
    import html

    inner = re.search(r"<article>(.*?)</article>", page, re.S)[1]
    lines = [" ".join(html.unescape(re.sub(r"<(?:/?b|a [^>]*|/a)>", "", re.sub(r"<br ?/?>", " ", part))).split()) for part in re.split(r"</?(?:p|h1|h2|h3|ul|ol|li|div|blockquote|table|tr|td|pre)(?:\s[^>]*)?>", inner)]
    return "\n".join(filter(None, lines))


@pytest.mark.parametrize("renamed", [False, True])
def test_given_pages(spark, renamed):
    """All given pages give their article's text; with class names replaced by random ones too, as the tree decides."""
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet").select("page_id", "url", "html")
    rows = pages.collect()
    want = {r["page_id"]: article_text(r["html"]) for r in rows}
    if renamed:
        name = {h: f"q{i}z" for i, h in enumerate(sorted({r["url"].split("/")[2] for r in rows}))}
        pages = spark.createDataFrame([(r["page_id"], r["url"], re.sub(r"class=\"[^\"]*\"", f'class="{name[r["url"].split("/")[2]]}"', r["html"])) for r in rows], "page_id bigint, url string, html string")
    got = html_tree.extract(pages).collect()
    assert {r["page_id"]: r["text"] for r in got} == want
    assert sum(r["n_decided_by_tree"] for r in got) > len(got) / 2


def test_style_tree_importance(spark):
    """Composite importance equals the recursion from the leaves up, by hand."""
    rows = [(i, f"http://h.x/{i}", f"<body><div><p>same</p></div><section><p>own {i}</p>{'<p>more</p>' * (i % 2)}</section></body>") for i in range(4)]
    tree = html_tree.places(html_tree.parsed_pages(spark.createDataFrame(rows, "page_id bigint, url string, html string")).cache())
    nodes = {r["place"]: r for r in tree.collect()}
    kids: dict = {}
    for r in nodes.values():
        if r["path"]:
            kids.setdefault(r["path"][-1], []).append(r)

    def composite(r):
        if r["leaf"]:
            return r["own"]
        rest = html_tree.DECAY ** r["kinds"]
        return (1 - rest) * r["own"] + rest * sum(k["share"] / r["pages"] * composite(k) for k in kids.get(r["place"], []))

    got = {r["place"]: r["importance"] for r in html_tree.importance(tree).collect()}
    assert got.keys() == nodes.keys()
    for place, r in nodes.items():
        assert got[place] == pytest.approx(composite(r))
    assert len(nodes) == 8 and min(r["own"] for r in nodes.values() if r["leaf"]) == 0


def test_style_tree_deep_nesting(spark):
    import tracemalloc

    deep = "<body>" + "<div>" * 100_000 + "deep text" + "</div>" * 100_000
    tracemalloc.start()
    made = html_tree.parse(deep)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert [t for _, _, _, t in made.blocks] == ["deep text"] and peak < 150e6
    df = spark.createDataFrame([(1, "http://d.x/1", deep), (2, None, "<p>a<!-- cut"), (3, "u", "<p>b <a href='x"), (4, "u", "plain"), (5, "u", " <ul><li>x<li>y</ul>")], "page_id bigint, url string, html string")
    assert {r["page_id"]: r["text"] for r in html_tree.extract(df).collect()} == {1: "deep text", 2: "a", 3: "b", 4: "plain", 5: "x\ny"}


def test_lm_scoring_orders_by_likeness(docs, labels):
    trusted = labels.where("quality = 1")
    rows = lm_scoring.apply(docs, trusted).join(labels, "doc_id").collect()
    good, bad = ([r["score"] for r in rows if r["quality"] == q] for q in (1, 0))
    assert np.median(good) < np.median(bad)


def exact_models(own, good, leave=None):
    """Word, bigram and history counts of both models without one document, from plain counters."""
    out = []
    for some in ([k for k in own if k in good], list(own)):
        uni, pair = Counter(), Counter()
        for k in some:
            if k != leave:
                uni.update(own[k])
                pair.update(zip(own[k], own[k][1:], strict=False))
        follow = Counter()
        for (h, _), n in pair.items():
            follow[h] += n
        out.append((uni, pair, follow, sum(uni.values())))
    return out


def lm_words(docs):
    own = {k: re.findall(rb"[^\x20\x09-\x0D]+", t.encode().lower()) for k, t in texts(docs).items()}
    seen = Counter(w for words in own.values() for w in words)
    return {k: [w if seen[w] > 1 else None for w in words] for k, words in own.items()}, sum(n > 1 for n in seen.values())


def lm_probability(model, scale, n_vocab, w, h=Ellipsis):
    uni, pair, follow, total = model
    p = (scale * uni[w] + 0.5) / (scale * total + 0.5 * (n_vocab + 1))
    return p if h is Ellipsis else (scale * pair[h, w] + 2.0 * p) / (scale * follow[h] + 2.0)


def test_lm_models_add_up_to_one(docs, labels):
    good = {r["doc_id"] for r in labels.where("quality = 1").collect()}
    own, n_vocab = lm_words(docs)
    words = sorted({w for x in own.values() for w in x if w is not None}) + [None]
    assert len(words) == n_vocab + 1
    for (uni, pair, follow, total), scale in zip(exact_models(own, good), (1.0, 0.3), strict=True):
        p = lm_scoring.unigram(scale * np.array([uni[w] for w in words]), scale * total, n_vocab)
        assert p.sum() == pytest.approx(1, abs=1e-9)
        for h in [w for w, _ in uni.most_common(25)] + [None] + words[: len(words) - 1 : max(1, len(words) // 25)]:
            assert lm_scoring.bigram(scale * np.array([pair[h, w] for w in words]), scale * follow[h], p).sum() == pytest.approx(1, abs=1e-9)


def test_lm_scoring_equals_exact_counts(docs, labels):
    """Every score, the document's own counts left out, whatever the chunks and buckets."""
    trusted = labels.where("quality = 1")
    good = {r["doc_id"] for r in trusted.collect()}
    own, n_vocab = lm_words(docs)
    whole = exact_models(own, good)
    scale = whole[0][3] / whole[1][3]

    def without(model, words):
        uni, pair, follow, total = model
        less, pairs, heads = Counter(words), Counter(zip(words, words[1:], strict=False)), Counter(words[:-1])
        return ({w: uni[w] - less[w] for w in less}, {p: pair[p] - pairs[p] for p in pairs}, {h: follow[h] - heads[h] for h in heads}, total - len(words))

    def loss(words, model, scale):
        p = [lm_probability(model, scale, n_vocab, w, *([words[i - 1]] if i else [])) for i, w in enumerate(words)]
        return -sum(map(np.log, p)) / max(1, len(words))

    for sizes in ({}, {"chunk_words": 20_000, "bucket_keys": 20_000}):
        rows = lm_scoring.apply(docs, trusted, **sizes).collect()
        assert sorted(r["doc_id"] for r in rows) == sorted(own)
        for r in rows:
            words = own[r["doc_id"]]
            assert (r["n_words"], r["n_unknown"]) == (len(words), words.count(None))
            target = without(whole[0], words) if r["doc_id"] in good else whole[0]
            assert [r["ce_target"], r["ce_background"]] == pytest.approx([loss(words, target, 1.0), loss(words, without(whole[1], words), scale)], abs=1e-9)
            assert r["target_like"] == (len(words) > 0 and r["score"] <= r["threshold"]) and r["trusted"] == (r["doc_id"] in good)
        mine = [r["target_like"] for r in rows if r["trusted"]]
        assert 0.78 * len(mine) <= sum(mine) <= 0.83 * len(mine) + 1


def test_languages_that_tie(spark):
    rows = [(i, "same words in both languages", "bb" if i % 2 else "aa") for i in range(40)] + [(100, "quite other letters xyz", "cc"), (101, "zyx xyz quite", "cc"), (104, "xyz zyx", "cc")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, lang string")
    got = {r["doc_id"]: r for r in langid.apply(df).collect()}
    even = {(r["lang_pred"], r["ambiguous"]) for k, r in got.items() if k < 100}
    assert even == {("aa", True)} or all(p in ("aa", "bb") and a for p, a in even)  # equal losses: the first by name
    assert got[100]["lang_pred"] == "cc"


def test_one_very_long_text(spark, docs, labels, small):
    """A text of several passes among short ones: counts, ids and spans as for any text."""
    parts = [t for t in texts(docs).values() if t]
    long = "\n".join(parts * (1 + 5_000_000 // sum(map(len, parts))))
    assert len(long.encode()) > 2 * common.PASS_BYTES
    df = spark.createDataFrame([(1, "short text"), (2, long), (3, None), (4, long[:1000])], "doc_id bigint, text string")
    trusted = labels.where("quality = 1")
    field = quality_crf.train(docs, labels)
    scored = {r["doc_id"]: r for r in quality_crf.score(df, field).collect()}
    assert 0 <= scored[2]["score"] <= 1 and scored[2]["n_lines"] == sum(bool(x.strip(" \t\n\r\x0b\x0c")) for x in long.split("\n"))
    counts = {r["doc_id"]: r for r in quality_rules.apply(df, trusted).collect()}
    assert counts[2]["n_words"] == len(re.findall(r"[^\x20\x09-\x0D]+", long)) and counts[2]["n_repeat_words"] > 0.9 * counts[2]["n_words"]
    bench = spark.read.parquet(f"{small}/benchmark.parquet")
    found = {r["doc_id"]: r for r in decontam.apply(df, bench).collect()}
    whole = decontam.apply(docs, bench).agg({"n_words": "sum"}).first()[0]
    assert found[2]["n_words"] == whole * (len(long) + 1) // (sum(map(len, parts)) + len(parts)) and found[2]["contaminated"]
    want = np.asarray(Tokenizer.from_file(WORD).encode(long, add_special_tokens=False).ids + [1], "<u4").tobytes()
    assert {r["doc_id"]: r["ids_crc32"] for r in token_store.write_store(df, WORD).records().collect()}[2] == zlib.crc32(want)
    ids = np.asarray(Tokenizer.from_file(BYTE).encode(long, add_special_tokens=False).ids + [1], "<u4")
    pieces = sorted((r["start"], r["length"], r["ids_crc32"]) for r in packing.pack(df, BYTE).where("doc_id = 2").collect())
    assert all(zlib.crc32(ids[a : a + n].tobytes()) == c for a, n, c in pieces) and sum(n for _, n, _ in pieces) == len(ids)
    spans = {r["doc_id"]: r["base_sha256"] for r in pii.find(df, None).collect()}
    assert spans[2] == hashlib.sha256(plain_spans(long).encode()).hexdigest()
    for made in (langid.predict(df, langid.train(docs)), lm_scoring.apply(df, trusted), simhash.cluster(df)):
        assert made.count() == 4


def test_clashing_columns(spark, docs, labels, small):
    """Tables whose own columns bear the names that operators use keep them as they are."""
    names = ["id", "text_hash", "row", "key", "hash", "root", "host", "place", "__text", "__id", "b", "kept"]
    df = docs.limit(30).selectExpr("doc_id", "text", "n_chars", *[f"concat('{n}', doc_id) as `{n}`" for n in names])
    bench = spark.read.parquet(f"{small}/benchmark.parquet")
    for kept in (quality_crf.keep(df, docs, labels), simhash.keep_one(df), decontam.keep_clean(df, bench), pii.redact(df, docs)):
        rows = kept.collect()
        assert kept.columns == df.columns and rows and all(r[n] == f"{n}{r['doc_id']}" for r in rows for n in names)


def test_empty_tables(spark, empty, labels, small):
    bench = spark.read.parquet(f"{small}/benchmark.parquet")
    trusted = labels.where("quality = 1")
    for df in (quality_crf.apply(empty, labels), quality_rules.apply(empty, trusted), simhash.cluster(empty), lm_scoring.apply(empty, trusted), langid.apply(empty), decontam.apply(empty, bench), packing.pack(empty, BYTE), token_store.write_store(empty, WORD).records(), pii.apply(empty), quality_crf.keep(empty, empty, labels), simhash.keep_one(empty), decontam.keep_clean(empty, bench), pii.redact(empty, empty), html_tree.extract(spark.createDataFrame([], "page_id bigint, url string, html string"))):
        assert df.count() == 0


def test_odd_tables(odd, docs, labels, spark):
    n = odd.count()
    trusted = labels.where("quality = 1")
    scored = quality_crf.score(odd, quality_crf.train(docs, labels)).collect()
    assert len(scored) == n and all(0 <= r["score"] <= 1 for r in scored)
    assert quality_crf.keep(odd, docs, labels).columns == odd.columns
    assert lm_scoring.apply(odd, trusted).count() == n
    langs = {r["doc_id"]: r["lang_pred"] for r in langid.predict(odd, langid.train(docs)).collect()}
    assert langs[0] == langs[1] == langs[4] == "und" and langs[6] != "und"
    kept = simhash.keep_one(odd)
    assert kept.columns == odd.columns and kept.where("doc_id is null").count() == 1
    assert decontam.apply(odd, spark.createDataFrame([], "item_id bigint, text string")).where("contaminated").count() == 0
