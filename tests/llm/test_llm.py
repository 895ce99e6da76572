"""Each operator against a plain version of itself, and on nulls, empty and long texts, ties, repeated rows and empty tables."""

import hashlib
import itertools
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
import sentencepiece
import xxhash
import zstandard
from hypothesis import given, settings
from hypothesis import strategies as st

import corpus_pipeline
from episodeflow.llm import components, decontaminate, language, onebit, packing, pii, quality, repair, simhash, token_cache, url_rules
from episodeflow.llm.common import materialise, smallest
from episodeflow.llm.tokens import encoder

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
ENC = "byte_bpe_50k.json"
ALPHABET = ["\u3000", "\u2009", "\x85", "×", "Ж", "ж,", "l'", "it's", ".", "12.5", "word ", "\u0301", "€", "verylongwordindeedlongerthansixteen", " ", " x", "\n", "\t", "a", "bc", "'s", "1", "!", "é", "<|endoftext|>", "\0", "x y z ", "\x01", "\r", "\xa0", "\x1c", "hello", "  "]


def docs(spark, texts, lang="en"):
    return spark.createDataFrame([(i, t, lang, "s", len(t or "")) for i, t in enumerate(texts)], DOCS)


AWKWARD = [None, "", " ", "a", "a", "word " * 3000, "x" * 5000, "é" * 50, "1" * 3000, "\n\n\n", "A b C"]


# ---- tokens


@settings(max_examples=400, deadline=None)
@given(st.lists(st.lists(st.sampled_from(ALPHABET), max_size=10).map("".join), max_size=6))
def test_pieces_give_the_library_s_ids(texts):
    e = encoder(ENC)
    flat, lengths = e.encode_all(texts)
    whole = [e.whole(t) for t in texts]
    assert lengths.tolist() == [len(w) for w in whole]
    assert np.array_equal(flat, np.concatenate(whole) if whole else flat)


@settings(max_examples=300, deadline=None)
@given(st.text(max_size=60))
def test_any_text_gives_the_library_s_ids(text):
    text = text.encode("utf-8", "ignore").decode()
    e = encoder(ENC)
    assert np.array_equal(e.encode(text), e.whole(text))


# ---- one-bit codes


def test_neighbours_equal_brute_force(spark):
    rng = np.random.default_rng(5)
    x = rng.normal(size=(1500, 16)).astype(np.float32)
    x[100:160] = x[3]  # ties
    rows = [(i, v.tolist()) for i, v in enumerate(x)]
    rows += [(5000, None), (5001, [0.0] * 16), (5002, [float("nan")] * 16), (5003, [float("inf")] + [0.0] * 15), (5004, [None] * 16), (5020, [0.0] * 16)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = defaultdict(list)
    for r in onebit.search(df, df.where("vec_id % 20 = 0"), 20).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append((r["vec_id"], r["score"]))
    assert set(got) == set(range(0, 1500, 20))
    hits = total = 0
    for q, found in got.items():
        s = onebit.exact(x.astype(np.float64), x[q].astype(np.float64))
        want = [int(i) for i in np.lexsort((np.arange(1500), -s)) if i != q][:20]
        hits, total = hits + len(set(want) & {i for i, _ in found}), total + 20
        assert all(abs(s[i] - v) < 1e-12 for i, v in found)
        assert found == sorted(found, key=lambda p: (-p[1], p[0]))
    assert hits / total >= 0.98


def test_estimates_stay_within_their_bounds():
    rng = np.random.default_rng(1)
    x, q, turn = rng.normal(size=(400, 64)), rng.normal(size=(50, 64)), onebit.rotation(64)
    codes, norm, held = onebit.encode(x, np.zeros(64), turn)
    guess, error = onebit.estimates(codes, norm, held, q, turn)
    assert np.mean(np.abs(guess - q @ x.T) <= error) > 0.98


def test_vectors_of_any_finite_length(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(200, 8))
    x[:60] *= 1e38
    x[60:70] *= 1e-40
    x = np.clip(x, -3e38, 3e38).astype(np.float32).astype(np.float64)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)] + [(900 + i, [1.0] * 9) for i in range(5)], "vec_id long, embedding array<double>")
    got = defaultdict(list)
    for r in onebit.search(df.repartition(5), df.where("vec_id % 20 = 0")).orderBy("rank").collect():
        got[r["query_id"]].append(r["vec_id"])
    want = {}
    for q in range(0, 200, 20):
        s = onebit.exact(x, x[q][None, :])
        want[q] = [int(i) for i in np.lexsort((np.arange(200), -s)) if i != q][:20]
    assert got == want


def test_repeated_and_clashing_vectors(spark, monkeypatch):
    monkeypatch.setattr(onebit, "QUERIES", 2)
    rows = [(20 * (i % 5), [float(i % 3), 1.0], i) for i in range(25)] + [(7, [1.0, 1.0], 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, score long").withColumnRenamed("score", "rank")
    got = onebit.search(df, df.where("vec_id % 20 = 0"), 4).collect()
    assert sorted((r["query_id"], r["rank"]) for r in got) == [(20 * q, k) for q in range(5) for k in (1, 2, 3, 4)]
    assert all(r["vec_id"] != r["query_id"] for r in got)


def test_few_vectors(spark):
    df = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.5, 0.5])], "vec_id long, embedding array<float>")
    assert [tuple(r) for r in onebit.search(df, df.where("vec_id % 20 = 0")).collect()] == [(0, 1, 1, 0.5)]
    assert onebit.search(df.where("false"), df.where("false")).count() == 0


# ---- grammar compression


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 12), max_size=400), st.integers(0, 400), st.integers(0, 50))
def test_grammar_round_trip(ids, at, n):
    ids = np.array(ids, np.uint32)
    first = int(ids.max()) + 1 if len(ids) else 1
    rules, spans, seq = repair.compress(ids, first, min_pair=2)
    shard = repair.Shard(repair.pack([1, None], np.array([len(ids) // 2, len(ids) - len(ids) // 2], np.uint32), ids))
    assert np.array_equal(shard.decode(), ids)
    at = min(at, len(ids))
    n = min(n, len(ids) - at)
    assert np.array_equal(shard.slice(at, n), ids[at : at + n])
    assert np.array_equal(shard.document(1), ids[len(ids) // 2 :])
    assert int(spans[seq[seq >= first] - first].sum()) + int((seq < first).sum()) == len(ids)
    assert all((r < first + k).all() for k, r in enumerate(rules))


def test_grammar_finds_repeats():
    ids = np.tile(np.arange(50, dtype=np.uint32), 400)
    _, _, seq = repair.compress(ids, 50)
    assert len(seq) < len(ids) / 20


def pair_by_pair(ids, first, least):
    """The most frequent pair again and again, one at a time."""
    seq, rules = ids.tolist(), 0
    while True:
        counts = Counter(zip(seq, seq[1:]))
        pair, n = max(counts.items(), key=lambda x: (x[1], x[0]), default=(None, 0))
        if n < least:
            return rules, seq
        out, i = [], 0
        while i < len(seq):
            hit = i + 1 < len(seq) and (seq[i], seq[i + 1]) == pair
            out.append(first + rules if hit else seq[i])
            i += 2 if hit else 1
        seq, rules = out, rules + 1


def test_grammar_leaves_no_frequent_pair(spark):
    rng = np.random.default_rng(3)
    words = [rng.integers(0, 300, rng.integers(2, 6)) for _ in range(150)]
    ids = np.concatenate([words[int(k)] for k in np.minimum(rng.zipf(1.3, 4000) - 1, 149)]).astype(np.uint32)
    for tokens in (ids, np.tile(np.arange(7, dtype=np.uint32), 900), np.zeros(5000, np.uint32)):
        rules, spans, seq = repair.compress(tokens, 300)
        assert max(Counter(zip(seq.tolist(), seq[1:].tolist())).values(), default=0) < repair.MIN_PAIR
        size = len(seq) + 3 * len(rules)
        if tokens is ids:
            plain_rules, plain_seq = pair_by_pair(tokens, 300, repair.MIN_PAIR)
            assert size <= 1.2 * (len(plain_seq) + 3 * plain_rules)
        else:  # rounds take all pairs of a period at once
            assert size < len(tokens) / 25


def test_null_and_extreme_doc_ids_stay_apart(spark):
    least = -(1 << 63)
    df = spark.createDataFrame([(None, "a b"), (least, "c d e"), (least, "c d e"), (5, None)], "doc_id long, text string")
    rows = sorted(((r["doc_id"] is not None, r["doc_id"] or 0, r["start"], r["n_tokens"]) for r in repair.digest(df).collect()))
    assert rows == [(False, 0, 0, 3), (True, least, 3, 4), (True, least, 7, 4), (True, 5, 11, 1)]


def test_shards_digest(spark, tmp_path):
    texts = [*AWKWARD, *[f"alpha beta {i % 7} gamma" * (i % 5) for i in range(60)]]
    e, at = encoder(ENC), 0
    got = {r["doc_id"]: r for r in repair.digest(docs(spark, texts)).collect()}
    for i, t in enumerate(texts):
        ids = np.append(e.whole(t or ""), 0).astype("<u4")
        assert (got[i]["start"], got[i]["n_tokens"], got[i]["ids_crc32"]) == (at, len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)
    assert repair.digest(docs(spark, [])).count() == 0
    repair.write_shards(docs(spark, texts), f"{tmp_path}/s", parts=2, shard_tokens=500)
    assert repair.read_shards(spark, f"{tmp_path}/s").count() == len(texts)


# ---- personal data

PATTERNS = [
    ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"),
    ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"),
    ("card", r"[0-9]([\x20-]?[0-9])+"),
    ("phone", r"\+[0-9][\x20().0-9-]+[0-9]"),
]


def luhn(d):
    return sum(int(c) if i % 2 == 0 else int(c) * 2 - 9 * (int(c) > 4) for i, c in enumerate(reversed(d))) % 10 == 0


def base_spans(text):
    out = []
    for kind, pattern in PATTERNS:
        for m in re.finditer(pattern, text):
            digits = re.sub("[^0-9]", "", m.group())
            if {"email": True, "ip": all(int(p) <= 255 for p in m.group().split(".")) if kind == "ip" else 0, "card": 13 <= len(digits) <= 19 and luhn(digits), "phone": 9 <= len(digits) <= 15}[kind]:
                out.append(f"{kind}:{m.start()}:{m.end()}")
    return out


def test_personal_data_equals_plain_patterns(spark):
    rng = random.Random(3)
    bits = ["1", "23", "4111 1111 1111 1111", "4111-1111-1111-1112", ".", "-", " ", "+33 1 23 45 67 89", "a@b.c", "@", "x_", "b.c", "é", "255.", "10.0.0.1", "999.1.1.1", "\U0001f600", "+", "(", "0000255."]
    texts = ["".join(rng.choice(bits) for _ in range(rng.randint(0, 25))) for _ in range(400)]
    texts += [*AWKWARD, "1" * 30000, "a" * 30000, "1 " * 10000, "a@b.cc " * 500, "+1" * 5000, "1.2" * 5000]
    rows = {r["doc_id"]: r for r in pii.report(docs(spark, texts)).collect()}
    for i, t in enumerate(texts):
        want = base_spans(t or "")
        assert [rows[i][f"n_{k}"] for k, _ in PATTERNS] == [sum(w.startswith(k + ":") for w in want) for k, _ in PATTERNS]
        assert rows[i]["base_sha256"] == hashlib.sha256(",".join(want).encode()).hexdigest()
        assert rows[i]["spans"].startswith(",".join(want))
    assert pii.report(docs(spark, [])).count() == 0


def test_context_and_checksums(spark):
    texts = ["IBAN GB82 WEST 1234 5698 7654 32.", "GB83 WEST 1234 5698 7654 32", "ssn: 123-45-6789", "part 123-45-6789", "see 10.0.0.1", "server 10.0.0.1"]
    rows = {r["doc_id"]: r for r in pii.report(docs(spark, texts)).collect()}
    assert [rows[i]["spans"] for i in range(4)] == ["iban:5:32", "", "ssn:5:16", ""]
    assert rows[4]["max_score"] < rows[5]["max_score"]
    red = pii.redact(docs(spark, [*texts, None, "é a@b.org é +33 1 23 45 67 89"]), ["doc_id", "text", "lang"]).orderBy("doc_id").collect()
    assert red[0]["text"] == "IBAN <iban>." and red[6]["text"] is None and red[7]["text"] == "é <email> é <phone>" and red[1]["text"] == texts[1]


def test_account_numbers_before_words_and_numbers(spark):
    own, spaced = "DE89370400440532013000", "GB82 WEST 1234 5698 7654 32"
    texts = [f"{own} Please pay", f"{own} BIC COBADEFF", f"é {own} 5 times", f"{spaced} THEN 77 MORE", f"{own} {spaced} {own}", f"{own}please", "GB82 WEST 1234 5698 7654 33 AND SO ON", f"{own} {own} " * 3, "NO9386011117947", "NO9386011117947 " + "A" * 30, f"{own}", f"x{own}"]
    rows = {r["doc_id"]: r["spans"] for r in pii.report(docs(spark, texts)).collect()}
    only = {i: ",".join(x for x in v.split(",") if x.startswith("iban")) for i, v in rows.items()}
    assert [only[i] for i in (0, 1, 2, 3)] == ["iban:0:22", "iban:0:22", "iban:2:24", "iban:0:27"]
    assert only[4] == "iban:0:22,iban:23:50,iban:51:73" and only[5] == only[6] == only[11] == ""
    assert only[7] == ",".join(f"iban:{23 * k}:{23 * k + 22}" for k in range(6))
    assert only[8] == only[9] == "iban:0:15" and only[10] == "iban:0:22"
    red = pii.redact(docs(spark, [texts[0]]), ["doc_id", "text"]).first()["text"]
    assert red == "<iban> Please pay"
    check = lambda c, body: f"{98 - int(''.join(str(int(x, 36)) for x in body + c + '00')) % 97:02d}"
    inner = "QQ" + check("QQ", "ABCDEFGHIJKLMNOP") + " ABCD EFGH IJKL MNOP"
    outer = "ZZ" + check("ZZ", inner[:14].replace(" ", "")) + " " + inner  # each valid, the second begins within the first
    assert [pii.report(docs(spark, [x])).first()["spans"] for x in (inner, outer)] == ["iban:0:24", "iban:0:19"]
    score = pii.find(docs(spark, [f"{own} 5 is my bank", f"{own} " + "." * 36 + " bank"])).orderBy("doc_id").collect()
    assert [round(r["_spans"]["iban"][0]["score"], 2) for r in score] == [1.0, 0.9]


def test_context_reaches_over_other_matches(spark):
    texts = ["SSN on file: 123-45-6789, 234-56-7890", "123-45-6789 and 234-56-7890 are tax numbers", "SSN 123-45-6789" + "," * 29 + "234-56-7890", "SSN 123-45-6789" + "," * 24 + "234-56-7890", "hosts: " + "10.0.0.1 " * 6]
    rows = {r["doc_id"]: r["spans"] for r in pii.report(docs(spark, texts)).collect()}
    assert [rows[i] for i in range(4)] == ["ssn:13:24,ssn:26:37", "ssn:0:11,ssn:16:27", "ssn:4:15", "ssn:4:15,ssn:39:50"]
    gaps = {r["doc_id"]: [round(x["score"], 2) for x in r["_spans"]["ip"]] for r in pii.find(docs(spark, texts)).collect()}
    assert gaps[4] == [0.95] * 4 + [0.6] * 2
    many = " ".join(f"{100 + i}-45-6789" for i in range(300)) + " ssn"
    assert pii.report(docs(spark, [many])).first()["spans"] == "ssn:3552:3563,ssn:3564:3575,ssn:3576:3587,ssn:3588:3599"
    red = pii.redact(docs(spark, texts[:1]), ["doc_id", "text"]).first()["text"]
    assert red == "SSN on file: <ssn>, <ssn>"


# ---- near-duplicates


def plain_print(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text))
    if not words:
        return 0
    hashes = [xxhash.xxh64_intdigest(" ".join(words[i : i + 3]).encode(), 42) for i in range(max(1, len(words) - 2))]
    return sum(1 << k for k in range(64) if 2 * sum(h >> k & 1 for h in hashes) > len(hashes))


def roots(nodes, edges):
    up = {n: n for n in nodes}

    def find(x):
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for a, b in edges:
        a, b = find(a), find(b)
        up[max(a, b)] = min(a, b)
    return {n: find(n) for n in nodes}


def test_components(spark):
    rng = random.Random(1)
    edges = [(rng.randrange(200), rng.randrange(200)) for _ in range(120)] + [(7, i) for i in range(300, 360)] + [(i, i + 1) for i in range(400, 440)] + [(9, 9), (None, 3)]
    df = spark.createDataFrame(edges, "a long, b long")
    real = [e for e in edges if None not in e]
    assert {r["node"]: r["component"] for r in components.components(df).collect()} == roots({x for e in real for x in e}, real)
    assert components.components(df.where("false")).count() == 0


def test_components_of_a_long_path(spark):
    path = [(i, i + 1) for i in range(300)]
    random.Random(2).shuffle(path)
    assert {r["component"] for r in components.components(spark.createDataFrame(path, "a long, b long")).collect()} == {0}


def test_near_duplicates_equal_brute_force(spark):
    rng = random.Random(8)
    base = [" ".join(rng.choice("alpha beta gamma delta eta theta iota".split()) + str(rng.randrange(30)) for _ in range(60)) for _ in range(12)]
    texts = [*AWKWARD, *base]
    for b in base[:6]:
        for _ in range(8):
            w = b.split()
            w[rng.randrange(60)] = "changed"
            texts.append(" ".join(w))
    texts += [base[0]] * 5
    rows = {r["doc_id"]: r for r in simhash.near_duplicates(docs(spark, texts)).collect()}
    prints = [plain_print(t or "") for t in texts]
    assert [int(rows[i]["fingerprint"], 16) for i in range(len(texts))] == prints
    links = [(i, j) for i in range(len(texts)) for j in range(i) if bin(prints[i] ^ prints[j]).count("1") <= 3]
    assert {i: r["component_id"] for i, r in rows.items()} == roots(range(len(texts)), links)
    kept = {r["doc_id"] for r in simhash.keep_one(docs(spark, texts)).collect()}
    assert kept == {i for i, r in rows.items() if r["component_id"] == i}
    assert simhash.near_duplicates(docs(spark, [])).count() == 0


def test_links_join_dense_groups(spark):
    rng = np.random.default_rng(1)
    have = set(rng.integers(0, 1 << 63, 200).astype(np.uint64).tolist())
    centre = next(iter(have))
    for _ in range(1200):
        y = centre
        for _ in range(rng.integers(1, 8)):
            y ^= 1 << int(rng.integers(0, 64))
        have.add(y)
    fps = np.array(sorted(have), np.uint64)
    signed = fps.view(np.int64).tolist()
    got = simhash.links(spark.createDataFrame([(x,) for x in signed], "fp long")).collect()
    want = [(signed[i], signed[i + 1 + j]) for i in range(len(fps)) for j in np.flatnonzero(np.bitwise_count(fps[i + 1 :] ^ fps[i]) <= 3)]
    assert roots(signed, [(r["a"], r["b"]) for r in got]) == roots(signed, want)
    for split in (1, 40):  # crowded cells split by their other half
        again = simhash.links(spark.createDataFrame([(x,) for x in signed], "fp long"), split=split).collect()
        assert roots(signed, [(r["a"], r["b"]) for r in again]) == roots(signed, want)
    a, b = fps[:200], fps[-200:]
    counts = lambda x: [bin(int(x) >> 2 * i & 3).count("1") for i in range(32)]
    d = simhash.manhattan(simhash.embedding(a), simhash.embedding(b))
    assert d.tolist() == [sum(abs(p - q) for p, q in zip(counts(x), counts(y))) for x, y in zip(a, b)]
    assert (d <= np.bitwise_count(a ^ b)).all()


# ---- token counts


def test_token_counts_and_cache(spark, tmp_path):
    texts, e = [*AWKWARD, "some words", "some words", "other <|endoftext|> words"], encoder(ENC)
    cache = f"{tmp_path}/cache"
    rows = {r["doc_id"]: r for r in token_cache.token_counts(docs(spark, texts), cache=cache, limit=2).collect()}
    for i, t in enumerate(texts):
        n = len(e.whole(t or ""))
        assert (rows[i]["n_bytes"], rows[i]["n_tokens"], rows[i]["over_limit"]) == (len((t or "").encode()), n, n > 2)
    size = spark.read.parquet(cache).count()
    assert size == len({t or "" for t in texts})
    again = token_cache.token_counts(docs(spark, [*texts, "new text"]), cache=cache).collect()
    assert len(again) == len(texts) + 1 and spark.read.parquet(cache).count() == size + 1
    assert token_cache.token_counts(docs(spark, [])).count() == 0
    again = token_cache.token_counts(docs(spark, texts), cache=cache)  # nothing is missing
    assert spark.read.parquet(cache).count() == size + 1 and {r["doc_id"]: r["n_tokens"] for r in again.collect()} == {i: r["n_tokens"] for i, r in rows.items()}
    pieces = token_cache.token_counts(docs(spark, ["hello world", None]), "piece_bpe_32k.model").collect()
    plain = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))
    assert {r["doc_id"]: r["n_tokens"] for r in pieces} == {0: len(plain.encode("hello world")), 1: 0}


# ---- language and quality

SAMPLES = {"en": "the cat and the dog were in the house with the other people of this town", "de": "der hund und die katze waren nicht in dem haus mit den anderen leuten dieser stadt", "fr": "le chien et le chat étaient dans la maison avec les autres gens de cette ville"}


def corpus(spark, n=240):
    rng = random.Random(2)
    rows = []
    for i in range(n):
        lang = sorted(SAMPLES)[i % 3]
        rows.append((i, " ".join(rng.choice(SAMPLES[lang].split()) for _ in range(40)), lang, "s", 0))
    rows += [(1000, None, "en", "s", 0), (1001, "", "de", "s", 0), (1002, "123 456 !!", None, "s", 0), (1003, "THE CAT AND THE DOG WERE IN THE HOUSE OF THIS TOWN", None, "s", 0)]
    return spark.createDataFrame(rows, DOCS)


def test_language_on_held_out_rows(spark):
    df = corpus(spark)
    rows = {r["doc_id"]: r for r in language.identify(df).collect()}
    truth = {r["doc_id"]: r["lang"] for r in df.collect()}
    held = [i for i in range(240) if zlib.crc32(str(i).encode()) % 4 == 2]
    assert {i for i in rows if rows[i]["held_out"]} == {i for i in rows if zlib.crc32(str(i).encode()) % 4 == 2}
    assert all(rows[i]["lang_pred"] == truth[i] and not rows[i]["rejected"] for i in held)
    assert [rows[i]["lang_pred"] for i in (1000, 1001, 1002, 1003)] == ["und", "und", "und", "en"]
    assert all(0 <= r["score"] <= 1 for r in rows.values())
    kept = language.known_language(df)
    assert kept.columns == df.columns and {r["doc_id"] for r in kept.collect()} == {i for i, r in rows.items() if not r["rejected"]}
    assert language.identify(df.where("false")).count() == 0
    assert {r["lang_pred"] for r in language.identify(df.withColumn("lang", df["lang"].substr(99, 1))).collect()} == {"und"}


def test_language_equals_plain_compression(spark):
    df = corpus(spark, 120)
    contents = language.fit(df, sample=30, content=2000, each=100)
    learned = {r["lang"]: r["n"] for r in df.where("text is not null and lang is not null").groupBy("lang").agg({"*": "count"}).withColumnRenamed("count(1)", "n").collect()}
    assert set(contents) == {"de", "en", "fr"} <= set(learned) and all(len(v) <= 2000 for v in contents.values())
    texts = [*AWKWARD, "the cat", "der hund und die katze", "le chat", "çà et là", "12", "the der le " * 2000]
    got = {r["doc_id"]: r for r in language.identify(docs(spark, texts), contents).collect()}
    for i, t in enumerate(texts):
        if not t or not any(c.isalpha() for c in t):
            assert (got[i]["lang_pred"], got[i]["score"], got[i]["rejected"]) == ("und", 0.0, True)
            continue
        plain, sizes = re.sub(r"[\W\d_]+", " ", t.lower()).encode(), {}
        for name, content in contents.items():
            made = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            press = zstandard.ZstdCompressor(dict_data=made, level=language.LEVEL, write_checksum=False, write_content_size=False, write_dict_id=False)
            sizes[name] = sum(len(press.compress(plain[a : a + 4096])) for a in range(0, len(plain), 4096))
        first, second = sorted(sizes.items(), key=lambda x: (x[1], x[0]))[:2]
        assert got[i]["lang_pred"] == first[0]
        assert got[i]["margin"] == (second[1] - first[1]) / second[1] and got[i]["rejected"] == (got[i]["margin"] < language.MARGIN)


def test_language_ties_go_to_the_first_name():
    judge = language.Judge({"b": b"same words here", "c": b"same words here", "a": b"same words here"})
    assert judge("some words")[0] == "b"  # fit hands them over in alphabetical order
    assert judge("some words")[2] == 0.0


def test_samples_are_the_smallest_hashes(spark):
    rows = [("x", i) for i in range(5000)] + [("y", i) for i in range(7)]
    df = spark.createDataFrame(rows, "k string, doc_id long")
    got = smallest(df, "k", 50).groupBy("k").count().collect()
    assert {r["k"]: r["count"] for r in got} == {"x": 50, "y": 7}
    top = df.where("k = 'x'").selectExpr("doc_id", "shiftrightunsigned(xxhash64(doc_id), 11) as h").orderBy("h").limit(50)
    assert {r[0] for r in smallest(df, "k", 50).where("k = 'x'").select("doc_id").collect()} == {r[0] for r in top.collect()}


def test_scores_equal_a_plain_network(spark):
    net = quality.Network()
    rng = np.random.default_rng(4)
    net.bias[:], net.shift = rng.normal(0, 0.2, len(net.bias)), np.float32(0.3)
    texts = [*[t for t in AWKWARD if t is not None], "abc", "abcd", "longer than one chunk " * 40, None]
    got = {r["doc_id"]: r["score"] for r in quality.score(docs(spark, texts), net).collect()}
    for i, t in enumerate(texts):
        data, pooled = (t or "").encode(), []
        for a in range(0, max(1, len(data)), quality.CHUNK):
            best = np.zeros(len(net.bias))
            for f in range(len(net.bias)):
                sums = [sum(float(net.table[j, data[k + j], f]) for j in range(quality.WIDTH)) + float(net.bias[f]) for k in range(a, min(a + quality.CHUNK, len(data) - quality.WIDTH + 1))]
                best[f] = max([0.0, *sums])
            pooled.append(best)
        z = np.concatenate([np.mean(pooled, axis=0), np.max(pooled, axis=0)]) @ net.out + float(net.shift)
        assert got[i] == pytest.approx(1 / (1 + np.exp(-z)), abs=1e-4), i


def test_training_moves_against_the_loss():
    texts, y = [b"good words of prose " * 3, b"JUNK!!! 111 $$$ " * 3] * 40, np.array([1, 0] * 40, np.float32)
    net = quality.Network()
    loss = lambda: float(np.mean([-np.log(p if t else 1 - p) for t, p in zip(y, net.score(np.frombuffer(b"".join(texts), np.uint8), np.cumsum([0, *map(len, texts)])))]))
    before = loss()
    net.fit(texts, y)
    assert loss() < 0.1 < before


def test_quality_on_held_out_rows(spark):
    rng = random.Random(6)
    rows, labels = [], []
    for i in range(400):
        good = i % 3 != 0
        words = [rng.choice(SAMPLES["en"].split()) for _ in range(60)]
        rows.append((i, " ".join(words if good else [w.upper() + "!!" for w in words]), "en", "s", 0))
        labels.append((i, int(good), 0))
    rows += [(900, None, None, "s", 0), (901, "", None, "s", 0), (902, "x" * 3000, None, "s", 0)]
    df = spark.createDataFrame(rows, DOCS)
    marks = spark.createDataFrame([*labels, (900, None, 0), (None, 1, 0)], "doc_id long, quality int, toxic int")
    got = {r["doc_id"]: r for r in quality.score(df, quality.fit(df, marks)).collect()}
    held = [i for i in range(400) if got[i]["held_out"]]
    assert sum(got[i]["predicted"] == int(i % 3 != 0) for i in held) / len(held) > 0.95
    assert len(got) == 403 and all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.7) for r in got.values())
    alone = quality.score(df, quality.fit(df, marks.where("false"))).first()
    assert alone["score"] == 0.5


def test_convolution_covers_the_whole_document():
    net = quality.Network()
    rng = np.random.default_rng(0)
    for n in (0, 1, 3, 255, 256, 257, 1000):
        data = rng.integers(0, 256, n).astype(np.uint8)
        codes, of = quality.chunked(data, np.array([0, n]))
        best = net.largest(codes).max(axis=0)
        padded = np.append(data.astype(int), [quality.PAD] * 4)
        want = np.array([sum(net.table[k, padded[i + k]] for k in range(4)) for i in range(max(1, n))])
        assert np.allclose(best, want.max(axis=0), atol=1e-5)


# ---- decontamination


def test_spaced_seeds_find_substituted_passages(spark):
    rng = random.Random(9)
    vocabulary = [f"w{i}" for i in range(4000)]
    item = lambda n: [rng.choice(vocabulary) for _ in range(n)]
    items = [item(30), item(18), item(6), item(3)]
    bench = spark.createDataFrame([(i, " ".join(x)) for i, x in enumerate(items)] + [(8, None), (9, "")], "item_id long, text string")
    changed = list(items[0])
    changed[5], changed[20] = "other", "thing"
    wrecked = [w if k % 3 else "no" for k, w in enumerate(items[0])]
    texts = [" ".join(item(50) + items[0] + item(40)), " ".join(item(9) + changed + item(9)), " ".join(item(20) + wrecked + item(20)), (" ".join(items[1])).upper(), " ".join(item(5) + items[2] + item(5)), " ".join(item(5) + items[3] + item(5)), " ".join(item(200)), None, "", " ".join(items[0][:8])]
    got = {(r["doc_id"], r["item_id"]): r for r in decontaminate.contaminated(docs(spark, texts), bench).collect()}
    assert set(got) == {(0, 0), (1, 0), (3, 1), (4, 2)}
    assert (got[0, 0]["start"], got[0, 0]["n_words"], got[1, 0]["n_equal"]) == (50, 30, 28)
    kept = sorted(r["doc_id"] for r in decontaminate.clean(docs(spark, texts), bench).collect())
    assert kept == [2, 5, 6, 7, 8, 9]
    assert decontaminate.contaminated(docs(spark, []), bench).count() == 0
    assert decontaminate.contaminated(docs(spark, texts), bench.where("false")).count() == 0


def test_no_overlap_of_four_fifths_is_missed(spark):
    rng = random.Random(12)
    vocabulary = [f"w{i}" for i in range(3000)]
    items, texts = [], []
    for n in [*range(5, 24), 29, 30, 40, 59]:
        for _ in range(6):
            own = [rng.choice(vocabulary) for _ in range(n)]
            changed = list(own)
            for k in rng.sample(range(n), n // 5):
                changed[k] = "x"
            items.append(" ".join(own))
            texts.append(" ".join([f"v{rng.randrange(999)}" for _ in range(7)] + changed + ["y", "z"]))
    for n, misses in ((5, 1), (6, 1), (11, 2), (12, 2), (15, 3)):  # every place
        for places in itertools.combinations(range(n), misses):
            items.append(" ".join(f"p{len(items)}q{k}" for k in range(n)))
            texts.append(" ".join("x" if k in places else w for k, w in enumerate(items[-1].split())))
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.contaminated(docs(spark, texts), bench).collect()}
    assert got == {(i, i) for i in range(len(items))}


def test_parts_of_items_and_inserted_words(spark):
    rng = random.Random(13)
    item = lambda n: [f"w{rng.randrange(9000)}" for _ in range(n)]
    items, texts, want = [], [], []
    for n, part in ((59, 29), (250, 100), (40, 12)):
        items.append(item(n))
        texts.append(item(5) + items[-1][7 : 7 + part] + item(5))
        want.append((part, part))
    for n in (5, 8, 12, 16, 23, 59):
        items += [item(n), item(n)]
        texts.append(item(5) + items[-2][: n // 2] + ["x"] + items[-2][n // 2 :] + item(5))
        texts.append(item(5) + items[-1][: n // 2] + items[-1][n // 2 + 1 :] + item(5))
        want += [(n + 1, n), (n - 1, n - 1)]
    # every tenth word dropped, no twelve words together
    items.append(item(59))
    texts.append([w for k, w in enumerate(items[-1]) if k % 10 != 9])
    want.append((54, 54))
    # four threes with a word inserted or dropped between
    items += [item(12), item(18)]
    texts += [[*items[-2][:3], "x", *items[-2][3:6], "x", *items[-2][6:9], "x", *items[-2][9:]], [w for k, w in enumerate(items[-1]) if k not in (3, 7, 11)][:12]]
    want += [(15, 12), (12, 12)]
    bench = spark.createDataFrame([(i, " ".join(x)) for i, x in enumerate(items)], "item_id long, text string")
    got = {r["doc_id"]: r for r in decontaminate.contaminated(docs(spark, [" ".join(x) for x in texts]), bench).collect()}
    assert {i: (r["n_words"], r["n_equal"]) for i, r in got.items()} == dict(enumerate(want))
    assert got[0]["start"] == 5 and got[0]["item_words"] == 59
    near = [items[0][:11], items[0][:3] + ["x"] + items[0][4:7] + ["x", "x"] + items[0][9:14]]  # too short, too far
    assert decontaminate.contaminated(docs(spark, [" ".join(x) for x in near]), bench).count() == 0


def plain_overlap(doc, item, least=12, similarity=0.8, most=16):
    """Whether any part of the document and any part of the item align with enough words and few enough misses."""
    best = {}
    whole = len(item) < least / similarity
    for i in range(len(item) + 1):
        for j in range(len(doc) + 1):
            ways = []
            if (i == 0) if len(item) < least else True:
                ways.append((0, 0, i, j))  # equal, misses, start in the item, start in the document
            for di, dj in ((1, 1), (1, 0), (0, 1)):
                for e, m, si, sj in best.get((i - di, j - dj), ()):
                    same = di and dj and item[i - 1] == doc[j - 1]
                    if m + (not same) <= most:
                        ways.append((e + same, m + (not same), si, sj))
            best[i, j] = set(ways)
            for e, m, si, sj in ways:
                if e and e >= similarity * (e + m) - 1e-9:
                    if (i == len(item) and si == 0 and whole) or (len(item) >= least and max(i - si, j - sj) >= least):
                        return True
    return False


def test_overlaps_equal_an_exhaustive_alignment(spark):
    rng = random.Random(21)
    items, texts, want = [], [], []
    for n in (6, 9, 13, 14):
        for _ in range(6):
            item = [f"w{rng.randrange(40)}" for _ in range(n)]
            doc = [f"w{rng.randrange(40)}" for _ in range(3)] + item + [f"w{rng.randrange(40)}" for _ in range(3)]
            for _ in range(rng.randint(0, 5)):
                k = rng.randrange(len(doc))
                doc[k : k + 1] = rng.choice(([], ["x"], [doc[k], "y"]))
            items.append(item)
            texts.append(doc)
    bench = spark.createDataFrame([(i, " ".join(x)) for i, x in enumerate(items)], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.contaminated(docs(spark, [" ".join(x) for x in texts]), bench).collect()}
    for i, item in enumerate(items):
        if plain_overlap(texts[i], item):
            want.append((i, i))
    assert len(want) > 8 and {x for x in got if x[0] == x[1]} == set(want)


def test_repeated_words_and_tiny_items(spark):
    rng = random.Random(1)
    items = ["ha " * 1000, "no yes " * 300, "only four words here", "one", "", "  ", " ".join(f"u{rng.randrange(99)}" for _ in range(40))]
    texts = ["ha " * 300_000, "no yes " * 50_000, "Only four -- words here!", "only four words here too", "one", "two", "", "ha " * 9 + "x", "ha " * 13 + "x"]
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    rows = {(r["doc_id"], r["item_id"]): r for r in decontaminate.contaminated(docs(spark, texts), bench).collect()}
    assert set(rows) == {(0, 0), (1, 1), (2, 2), (4, 3), (8, 0)}
    assert (rows[0, 0]["start"], rows[0, 0]["n_equal"], rows[1, 1]["n_equal"], rows[8, 0]["n_words"]) == (0, 1000, 600, 13)
    many = " ".join(f"a{i}" for i in range(400_000))  # over several parts
    data = np.frombuffer(many.encode(), np.uint8)
    whole = decontaminate.words(data, np.array([0, 7, 7, len(data)]), 1 << 30)
    for part in (1, 1000, 65_537):
        size = len(data) if part > 1 else 300
        a, b = decontaminate.words(data[:size], np.array([0, 7, 7, size]), part), decontaminate.words(data[:size], np.array([0, 7, 7, size]), 1 << 30)
        assert np.array_equal(a[0], b[0]) and np.array_equal(a[1], b[1])
    assert len(whole[0]) >= 400_000


def test_word_hashes_do_not_depend_on_the_place():
    h = lambda t: decontaminate.words(np.frombuffer(t.encode(), np.uint8), np.array([0, len(t.encode())]))[0].tolist()
    assert h("Alpha, beta") == h("  alpha -- BETA!") and h("alpha beta") != h("beta alpha") and h("") == []
    data = np.frombuffer(b"ab" + b"cd", np.uint8)
    hashes, firsts = decontaminate.words(data, np.array([0, 2, 4]))
    assert hashes.tolist() == h("ab cd") and firsts.tolist() == [0, 1, 2]


# ---- url rules


def test_url_rules_and_aliases(spark):
    canonical = '<html><link rel="canonical" href="{}"></html>'
    refresh = '<meta http-equiv="refresh" content="0; url={}">'
    pages = [
        (1, "https://x.example.org/es/1", ""),
        (2, "https://blog.net/a", canonical.format("https://www.example.org/es/9?x=1&amp;y=2")),
        (3, "https://blog.net/b#top", refresh.format("/a")),
        (4, "http://EXAMPLE.org/en/1", None),
        (5, "https://site.com/fr/", canonical.format("https://bad.com/de/1")),
        (6, None, canonical.format("https://bad.com/de/1")),
        (7, "no scheme", ""),
        (8, "https://blog.net/c", canonical.format("//bad.com/de/1")),
        (9, "https://bad.com/de/1?q#f", ""),
        (10, "https://other.net/", "<link rel='stylesheet' href='https://bad.com/de/1'>"),
        (11, "https://two.net/", canonical.format("https://bad.com/de/7")),
        (11, "https://two.net/", canonical.format("https://bad.com/de/7")),
        (12, "https://notorg/x", ""),
        (13, "https://example.org", ""),
    ]
    df = spark.createDataFrame(pages, "page_id long, url string, html string").withColumnRenamed("html", "html")
    rows = url_rules.judge(df).collect()
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in rows}
    assert len(rows) == 14
    assert got[1] == ("x.example.org", "/es/1", "example.org/es/", "block")
    assert got[2] == ("blog.net", "/a", None, "block") and got[3] == ("blog.net", "/b", None, "block")
    assert got[4][2:] == ("example.org/en/1", "block")
    assert got[5][2:] == ("com/fr/", "allow")
    assert got[6] == ("", "", None, "allow") == got[7]
    assert got[8][3] == "allow"  # its class holds an explicitly allowed page, which takes precedence
    assert got[9][2:] == ("com/de/", "block")
    assert got[10][3] == "allow" and got[11][3] == "block" and got[12][2] is None and got[13][:3] == ("example.org", "", None)
    assert url_rules.judge(df.where("false")).count() == 0


# ---- packing


def check_plan(plan, counts, limit):
    seen, used = Counter(), defaultdict(list)
    for length, rank, n, sequence, each, base in plan.rows:
        for i in range(n):
            seen[length, rank + i] += 1
            used[sequence + i // each].append((base + i % each * length, length))
    assert seen == Counter({(n, r): 1 for n, c in counts.items() for r in range(c)})
    for items in used.values():
        at = 0
        for offset, length in sorted(items):
            assert offset == at
            at += length
        assert at <= limit
    return len(used)


@settings(max_examples=40, deadline=None)
@given(st.dictionaries(st.integers(1, 40), st.integers(0, 30), max_size=25))
def test_plans_place_every_piece_once(counts):
    n = check_plan(packing.best_plan(counts, 40), counts, 40)
    total = sum(k * v for k, v in counts.items())
    assert n >= -(-total // 40)


def test_plans_are_tight():
    rng = np.random.default_rng(0)
    counts = Counter(np.clip(rng.lognormal(5.5, 1, 6000).astype(int), 1, 1024).tolist())
    total = sum(k * v for k, v in counts.items())
    assert check_plan(packing.best_plan(counts), counts, 1024) <= 1.01 * -(-total // 1024)
    halves = {500: 100, 524: 100}
    assert check_plan(packing.best_plan(halves), halves, 1024) == 100


def test_packed_documents(spark):
    texts, e = [*AWKWARD, *[f"word{i} " * (i * 7 % 900) for i in range(40)]], encoder(ENC)
    rows = packing.pack(docs(spark, texts)).collect()
    by_doc, used = defaultdict(list), defaultdict(list)
    for r in rows:
        by_doc[r["doc_id"]].append(r)
        used[r["sequence_id"]].append((r["offset"], r["length"]))
    assert set(by_doc) == set(range(len(texts)))
    for i, t in enumerate(texts):
        ids, at = np.append(e.whole(t or ""), 2).astype("<u4"), 0
        for k, r in enumerate(sorted(by_doc[i], key=lambda r: r["piece"])):
            assert (r["piece"], r["start"]) == (k, at) and (k == 0 or r["length"] == 1024)
            assert r["ids_crc32"] == zlib.crc32(ids[at : at + r["length"]].tobytes())
            at += r["length"]
        assert at == len(ids)
    for items in used.values():
        at = 0
        for offset, length in sorted(items):
            assert offset == at
            at += length
        assert at <= 1024
    assert packing.pack(docs(spark, [])).count() == 0
    twice = docs(spark, ["a b c"]).union(docs(spark, ["a b c"]))
    assert packing.pack(twice).count() == 2


# ---- nulls, repeated rows and names that clash


def test_every_operator_takes_repeated_and_null_doc_ids_and_clashing_names(spark):
    text = "the cat and the dog were in the house with the other people of this town"
    rows = [(1, text, "en"), (1, text, "en"), (None, text, "en"), (2, None, None), (None, None, None), (3, "bob@example.org " + text, "de")]
    names = ["ip", "email", "card", "phone", "iban", "ssn", "score", "digest", "fp", "node", "component", "cell", "length", "bucket", "row", "piece", "spans", "held_out", "item_id", "a", "b", "_k"]
    df = spark.createDataFrame([(*r, *["z"] * len(names)) for r in rows], ", ".join(["doc_id long", "text string", "lang string", *[f"`{n}` string" for n in names]]))
    bench = spark.createDataFrame([(1, "no words of the texts are in this item at all not even one or two", "z")], "item_id long, text string, doc_id string")
    marks = spark.createDataFrame([(1, 1, "z"), (3, 0, "z"), (None, 1, "z")], "doc_id long, quality int, text string")
    some = [r[0] for r in rows]
    for got in (repair.digest(df), pii.report(df), token_cache.token_counts(df), language.identify(df), quality.score(df, quality.fit(df, marks))):
        assert sorted(str(r["doc_id"]) for r in got.collect()) == sorted(map(str, some))
    assert simhash.near_duplicates(df).count() == len(rows)
    assert sorted(str(r["doc_id"]) for r in packing.pack(df).collect()) == sorted(map(str, some))
    assert decontaminate.contaminated(df, bench).count() == 0
    for name, stage in (("language", lambda: language.known_language(df)), ("near", lambda: simhash.keep_one(df)), ("clean", lambda: decontaminate.clean(df, bench)), ("redact", lambda: pii.redact(df, df.columns))):
        kept = stage()
        assert kept.columns == df.columns, name
        assert all(r["ip"] == r["_k"] == "z" for r in kept.collect()), name
    assert sorted(r["text"] for r in pii.redact(df, df.columns).collect() if r["text"])[0].startswith("<email> the")
    pages = spark.createDataFrame([(1, "https://a.org/x", "z", "z", "z"), (None, None, "z", "z", "z"), (1, "https://a.org/x", "z", "z", "z")], "page_id long, url string, html string, host string, verdict string")
    assert url_rules.judge(pages).count() == 3


def test_long_texts(spark):
    rng = random.Random(5)
    long = " ".join(rng.choice(SAMPLES["en"].split()) + str(rng.randrange(10**6)) for _ in range(400_000))
    df = docs(spark, [long, "the cat and the dog", long + " end"])
    assert language.identify(df).count() == quality.score(df, quality.Network()).count() == 3
    assert simhash.near_duplicates(df).select("component_id").distinct().count() == 2
    item = " ".join(long.split()[200_000:200_030])
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    assert sorted((r["doc_id"], r["start"]) for r in decontaminate.contaminated(df, bench).collect()) == [(0, 200_000), (2, 200_000)]
    packed = {r["doc_id"]: r["n"] for r in packing.pack(df).groupBy("doc_id").agg({"length": "sum"}).withColumnRenamed("sum(length)", "n").collect()}
    counted = {r["doc_id"]: r["n_tokens"] + 1 for r in token_cache.token_counts(df).collect()}
    assert packed == counted


# ---- the pipeline


def test_pipeline_stages(spark, tmp_path):
    rng = random.Random(4)
    vocabulary = {k: v.split() for k, v in SAMPLES.items()}
    rows = []
    for i in range(150):
        lang = sorted(SAMPLES)[i % 3]
        rows.append((i, " ".join(rng.choice(vocabulary[lang]) + (str(rng.randrange(500)) if rng.random() < 0.5 else "") for _ in range(80)), lang, "s", 0))
    item = "zebra yak xerus wolf vole urchin tapir seal rhino quail puma otter newt mole lynx koala jackal ibis"
    rows += [(200, rows[0][1], "de", "s", 0), (201, rows[1][1] + " the dog " + item, "en", "s", 0), (202, " ".join(rng.choice(vocabulary["en"]) + str(rng.randrange(900)) for _ in range(60)) + " mail bob@example.org now", "en", "s", 0), (203, "12 34", "en", "s", 0), (204, None, None, "s", 0)]
    spark.createDataFrame(rows, DOCS).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    kept, columns = spark.read.parquet(f"{tmp_path}/documents.parquet"), DOCS.replace(" long", "").replace(" string", "").split(", ")
    seen = []
    for name, stage in corpus_pipeline.STAGES:
        kept = materialise(stage(spark, kept, str(tmp_path)), name)
        seen.append({r["doc_id"]: r for r in kept.collect()} if name != "packing" else None)
        if name != "packing":
            assert kept.columns == columns
    lang, near, clean, red, _ = seen
    assert 203 not in lang and 204 not in lang and {200, 201, 202} <= set(lang)
    assert 200 not in near and 0 in near
    assert set(near) - set(clean) == {201}
    assert "<email>" in red[202]["text"] and set(red) == set(clean)
    got = {r["doc_id"] for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert got == set(red)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language", "near_duplicates", "decontamination", "personal_data", "packing"]


def test_clashing_columns_and_strange_schemas(spark):
    odd = docs(spark, ["the cat and the dog", None]).selectExpr("*", "1 AS digest", "'x' AS fp", "2 AS bucket", "3 AS length", "4 AS component_id", "5 AS cell", "6 AS piece")
    assert simhash.near_duplicates(odd).count() == 2 and simhash.keep_one(odd).columns == odd.columns
    assert token_cache.token_counts(odd).count() == 2 and packing.pack(odd).count() == 2 and repair.digest(odd).count() == 2
    assert pii.report(odd).count() == 2 and pii.redact(odd, odd.columns).columns == odd.columns
    assert language.identify(odd).count() == 2 and language.known_language(odd).columns == odd.columns


@pytest.mark.parametrize("name", ["op1_onebit_neighbours", "op9_url_rules"])
def test_sql_beside_queries(spark, name):
    import os

    from episodeflow.llm import queries

    sf = "/root/testdata/sf0.001"
    if not os.path.isdir(sf):
        pytest.skip("no test data")
    duckdb = pytest.importorskip("duckdb")
    con = duckdb.connect()
    for t in ("embeddings", "pages"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    got = con.execute(queries.oracle_sql()[name])
    columns = [c[0] for c in got.description]
    want = sorted(map(str, got.fetchall()))
    assert sorted(str(tuple(r[c] for c in columns)) for r in queries.queries()[name](spark, sf).collect()) == want


def test_rounds_look_at_part_of_the_places_and_find_what_all_give(monkeypatch):
    rng, real = np.random.default_rng(3), repair._frequent
    for k in range(60):
        ids = rng.integers(0, int(rng.integers(1, 12)), int(rng.integers(0, 500))).astype(np.uint32)
        ids = np.tile(ids[:30], 9) if k % 4 == 0 else ids
        first = int(ids.max()) + 1 if len(ids) else 1
        for every, least in ((4, 2), (64, 4)):
            got = repair.compress(ids, first, every, least)
            with monkeypatch.context() as m:
                m.setattr(repair, "_frequent", lambda seq, places, *rest: real(seq, np.arange(len(seq) - 1), *rest))
                want = repair.compress(ids, first, every, least)
            assert all(np.array_equal(a, b) for a, b in zip(got, want, strict=True))
