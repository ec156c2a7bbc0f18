"""The operators against brute force, the public libraries and their stated edge cases."""

import base64
import gzip
import hashlib
import random
import re
import urllib.parse
import zlib

import numpy as np
import public_tokenizers as P
import pytest
import sentencepiece
from tokenizers import Tokenizer

from polymetric.llm import bpe, decontam, exact_dedup, licenses, line_dedup, neardup, ngram_join, quality, secrets, sharding, token_counts
from polymetric.llm.common import Scratch, components

DOCS = "doc_id long, text string, lang string, source string, n_chars long, k string, bf_word string"
A = "one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen seventeen eighteen nineteen twenty"
ROWS = [
    (1, A, "en", "s", 1, "x", "y"), (2, A + " more", None, None, None, None, None), (3, A, "en", "s", 1, "x", "y"), (3, A, "en", "s", 1, "x", "y"), (4, None, "en", "s", 0, "", ""),
    (5, "", "en", "s", 0, "", ""), (None, "a b", "en", "s", 3, "", ""), (6, "line one is here and long enough\n\nline one is here and long enough!\nx", "en", "s", 1, "", ""), (7, "word " * 30_000, "en", "s", 1, "", ""), (8, A.upper(), "en", "s", 1, "", ""),
]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, DOCS)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


def test_empty_tables(spark, empty):
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    bench = spark.createDataFrame([], "item_id long, text string")
    model = quality.train(empty, labels)
    for df in (exact_dedup.exact_duplicates(empty), sharding.shard_by_size(empty, 4), secrets.scan_documents(empty), ngram_join.ngram_join(empty), line_dedup.duplicate_lines(empty), decontam.contaminated(empty, bench), quality.score_documents(empty, model), bpe.encode_documents(empty, P.path("byte_bpe_50k.json")), token_counts.count_tokens(empty, P.path("piece_bpe_32k.model"))):
        assert df.count() == 0


def test_exact_dedup(docs):
    got = {(r["doc_id"], r["keep_id"], r["group_size"], r["kept"]) for r in exact_dedup.exact_duplicates(docs).collect()}
    assert {(1, 8, 4, False), (3, 8, 4, False), (8, 8, 4, True), (4, 5, 2, False), (5, 5, 2, True), (None, None, 1, True)} <= got


def test_ngram_join(docs):
    got = {r["doc_id"]: (r["class_id"], r["n_links"], r["kept"]) for r in ngram_join.ngram_join(docs).collect()}
    assert got[1] == (1, 4, True) and got[2] == (1, 4, False) and got[8] == (1, 4, False)
    assert got[4] == (4, 1, True) and got[5] == (4, 1, False) and got[None] == (None, 0, True) and got[7] == (7, 0, True)


def test_line_dedup(docs):
    got = {r["doc_id"]: (r["n_lines"], r["dropped"]) for r in line_dedup.duplicate_lines(docs).collect()}
    assert got[1] == (1, []) and got[2] == (1, [0]) and got[8] == (1, [0]) and got[6] == (4, [2]) and got[4] == (1, [])
    cut = {r["doc_id"]: r["text"] for r in line_dedup.without_lines(docs, line_dedup.duplicate_lines(docs)).collect()}
    assert cut[6] == "line one is here and long enough\n\nx" and cut[2] == "" and cut[4] is None


def test_near_links_equal_brute_force_in_large_groups(spark):
    random.seed(5)
    base = [f"w{random.randrange(10**6)}" for _ in range(120)]
    rows = []
    for i in range(150):
        w = list(base)
        for p in random.sample(range(120), i % 4):
            w[p] = f"x{random.randrange(10**6)}"
        rows.append((i, " ".join(w)))
    sets = {i: {tuple(t.split()[j : j + 5]) for j in range(116)} for i, t in rows}
    links = {i: sum(9 * len(a & b) >= 4 * (len(a) + len(b)) for j, b in sets.items() if j != i) for i, a in sets.items()}
    got = {r["doc_id"]: r["n_links"] for r in ngram_join.ngram_join(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == links


def test_banding_reaches_its_recall():
    for recall in (0.9, 0.99, 0.999):
        b, r = neardup.banding(0.8, recall, 0.1)
        assert 1 - (1 - 0.8**r) ** b >= recall


def test_components_of_a_long_chain_and_a_hub(spark):
    edges = [(i, i + 1) for i in range(1, 60)] + [(1000, 1000 + i) for i in range(1, 50)]
    got = dict(map(tuple, components(spark.createDataFrame(edges, "u long, v long"), Scratch(spark)).collect()))
    assert got == {i: 1 for i in range(1, 61)} | {1000 + i: 1000 for i in range(50)}


def test_sharding(docs):
    rows = sharding.shard_by_size(docs, 3).collect()
    assert len(rows) == len(ROWS)
    for s in {r["shard"] for r in rows}:
        slots = sorted(r["slot"] for r in rows if r["shard"] == s)
        assert slots == list(range(len(slots)))
    assert len({r["shard"] for r in rows if r["doc_id"] in (1, 3)}) == 1 and {r["size"] for r in rows if r["doc_id"] in (4, 5)} == {16}
    assert all(r["text_crc32"] == zlib.crc32((ROWS[0][1]).encode()) for r in rows if r["doc_id"] == 1)


def test_schedule_is_the_plain_heap():
    import heapq

    rng = random.Random(4)
    classes = [(rng.randrange(1, 50), rng.randrange(1, 400)) for _ in range(30)]
    classes = list(dict(classes).items())
    heap = [(0, s) for s in range(7)]
    for size, n in sorted(classes, reverse=True):
        for _ in range(n):
            load, s = heap[0]
            heapq.heapreplace(heap, (load + size, s))
    got = [0] * 7
    for size, s, a, b in sharding.schedule(classes, 7):
        got[s] += size * (b - a)
    assert sorted(got) == sorted(x for x, _ in heap)


def test_secrets():
    key = "AKIA" + "Q" * 16
    layers = [key, urllib.parse.quote(key, safe="").replace("A", "%41"), base64.b64encode(("deep secret: " + "k" * 9).encode()).decode(), base64.b64encode(gzip.compress(b"token=abcdef123456")).decode(), base64.b64encode(base64.b64encode(b"password = hunter2hunter2")).decode(), "\\u0041KIA" + "Z" * 16]
    for x in layers:
        text = f"Ünï {x} end"
        base, full = secrets.scan(text)
        assert len(full) == 1 and len(base) == (x == key)
        (start, end, _) = full[0]
        assert 4 <= start < end <= 4 + len(x)
    assert secrets.find("secret:token: abcdefgh") == [] and secrets.find("ſecret=abcdefgh") == []
    assert secrets.find("f" * 23) == [] and secrets.find("f" * 24) == [(0, 24, "hex")]
    assert secrets.scan("%25" * 40 + "41")[1] == []


def test_secrets_in_layers_that_are_not_clean_text(monkeypatch):
    b64 = lambda x: base64.b64encode(x).decode()
    wrap = lambda x, n=76: "\n".join(x[i : i + n] for i in range(0, len(x), n))
    rng = random.Random(4)
    noise = bytes(rng.randrange(256) for _ in range(3000)).hex().upper().encode()
    secret, packed = b"password=hunter2hunter2", gzip.compress(noise + b" token=abcdef123456 " + noise)
    for x in (
        b64("password=hunter2hunter2".encode("utf-16")), b64("password=hunter2hunter2".encode("utf-16-be")), b64(b"user\0" + secret + b"\0x"), b64("größer ".encode("latin-1") + secret), b64(b"\x01" + secret),
        "%FF" + "".join(f"%{c:02X}" for c in secret), wrap(b64(packed)), "data:\n" + wrap(b64(packed)).replace("\n", "\r\n  "), wrap(b64(b"some plain text, " * 3 + secret), 64),
        b64(packed[:-9]), b64(packed + b"behind"), b64(packed[:-9] + b"\0\xff\xff\xff\xff"), b64(gzip.compress(b"nothing") + packed), b64(gzip.compress(b"nothing here") + secret), b64(gzip.compress(packed)), b64(zlib.compress(noise + secret)[:-3]),
    ):
        _, full = secrets.scan(f"Ünï {x} end")
        assert full and all(4 <= a < b <= 4 + len(x) for a, b, _ in full), x[:60]
    for name, n in (("PIECE", 2000), ("OVERLAP", 300)):
        monkeypatch.setattr(secrets, name, n)
    assert [k for _, _, k in secrets.scan(b64(packed))[1]] == ["assign"]


def test_secret_rows(docs):
    r = secrets.scan_documents(docs).where("doc_id = 4").first()
    assert (r["n_assign"], r["spans"], r["base_sha256"]) == (0, "", hashlib.sha256(b"").hexdigest())


TEXTS = ["", " ", "  a  b", "x<|endoftext|>y", "naïve 日本語 \U0001f600\t\ttab\r\n", "don't I'll", "a" * 300, " aa", "▁ <s> <0x0A>", "The thention,\n\nof reth. ", *(r[1] or "" for r in ROWS[:3])]


def test_token_counts_of_every_prefix():
    sp, c = sentencepiece.SentencePieceProcessor(model_file=P.path("piece_bpe_32k.model")), token_counts.PrefixCounter(P.path("piece_bpe_32k.model"))
    for t in TEXTS:
        want = [len(sp.encode(t[:k])) for k in range(len(t) + 1)]
        assert c.count(t) == want[-1] and c.prefixes(t) == want
        for limit in (1, 5, 40):
            assert c.fitting(t, limit) == max(k for k, n in enumerate(want) if n <= limit)


def test_bpe_equals_the_library():
    lib, own = Tokenizer.from_file(P.path("byte_bpe_50k.json")), bpe.BytePairs(P.path("byte_bpe_50k.json"))
    for t in TEXTS:
        want = lib.encode(t, add_special_tokens=False).ids
        assert own.encode(t).tolist() == want and own.decode(own.encode(t)) == lib.decode(want, skip_special_tokens=False) == t


def test_decontamination_equals_alignment():
    rng = random.Random(3)
    for _ in range(60):
        item = "".join(rng.choice("abcdefgh ") for _ in range(100))
        v = list(item)
        for _ in range(rng.randrange(14)):
            v[rng.randrange(100)] = rng.choice("abcdefgh ")
        text = "zz " + "".join(v) + " yy"
        row = [0] * (len(text) + 1)
        for i, a in enumerate(item, 1):
            left, row[0] = row[0], i
            for j, b in enumerate(text, 1):
                left, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, left + (a != b))
        (b,) = decontam.Benchmark.of([(1, item)], 8, 0.1)
        got = b.search([decontam.codes(decontam.normal(text))], b.table())
        assert bool(got) == (min(row) <= 10) and (not got or got[0][2] == min(row))


def test_quality_learns_and_never_sees_held_out_rows(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    s = quality.Settings(most_rows=300, epochs=6)
    assert quality.labelled_rows(docs, labels, s).where("pmod(crc32(cast(doc_id as string)), 5) = 0").count() == 0
    got = quality.score_documents(docs, quality.train(docs, labels, s)).join(labels, "doc_id").where("held_out").toPandas()
    assert ((got.score >= 0.3) == (got.quality == 1)).mean() > 0.97 and got.score.between(0, 1).all()


def test_licenses(spark):
    files = spark.createDataFrame([(1, "a/LICENSE", "Released under the MIT License."), (2, "a/b/c/x.py", "code"), (3, "a/b/COPYING", "Licensed under CC BY-NC 4.0."), (4, "a/b/c/y.py", "x\nLicensed under the Apache License, Version 2.0.\ny"), (5, "z/q.py", None), (6, None, "t")], "doc_id long, path string, text string")
    got = {r["doc_id"]: (r["license"], r["license_dir"]) for r in licenses.scan_licenses(files).collect()}
    assert got == {1: ("MIT", None), 2: ("CC-BY-NC-4.0", "a/b"), 3: ("CC-BY-NC-4.0", None), 4: ("Apache-2.0", None), 5: (None, None), 6: (None, None)}


def test_licenses_inside_lines(spark):
    apache, mit = licenses.TEMPLATES["Apache-2.0"][0], licenses.TEMPLATES["MIT"][1]
    around = "quick foxes jump over lazy dogs while seven wizards quietly mix new potions"
    cut = mit.split()
    texts = [f"{around}. {apache}. {around}", f"x\n{around}; {mit}; {around}", f"{around}\n" + "\n".join(" ".join(cut[i : i + 5]) for i in range(0, len(cut), 5)) + f"\n{around}", around]
    files = spark.createDataFrame([(i, f"f{i}", t) for i, t in enumerate(texts)], "doc_id long, path string, text string")
    got = {r["doc_id"]: (r["own_license"], r["own_line"]) for r in licenses.scan_licenses(files).collect()}
    assert got == {0: ("Apache-2.0", 0), 1: ("MIT", 1), 2: ("MIT", 1), 3: (None, None)}


def test_pipeline(spark):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    out = corpus_pipeline.run(spark, sf).toPandas()
    assert out.doc_id.is_unique and 0 < len(out) < spark.read.parquet(f"{sf}/documents.parquet").count()
    assert all(len(i) == n for i, n in zip(out.ids, out.n_tokens, strict=True))
    assert np.all([re.fullmatch("[0-9a-f]{64}", x) for x in out.ids_sha256])
