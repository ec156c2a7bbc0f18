"""The operators against brute force on small tables, planted pairs, and inputs that are meant to break them."""

import base64
import gzip
import random
import zlib

import pytest

from polymetric.llm import decontam, exact_dedup, licenses, line_dedup, neardup, ngram_join, quality, secrets, sharding


def _near(text: str, rng: random.Random, share: float, words: bool) -> str:
    cells = text.split() if words else list(text)
    for p in rng.sample(range(len(cells)), int(share * len(cells))):
        cells[p] = f"x{rng.randrange(10**6)}" if words else rng.choice("abcdefghijk")
    return (" " if words else "").join(cells)


def _classes(sets: dict, near) -> dict:
    """Least id of each connected component, all pairs compared."""
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(sets)
    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            if near(sets[a], sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


def _jaccard(a: set, b: set) -> bool:
    return 5 * len(a & b) >= 4 * len(a | b)


@pytest.fixture(scope="module")
def corpus():
    rng = random.Random(11)
    bases = [" ".join(f"w{rng.randrange(3000)}" for _ in range(rng.choice((7, 40, 120)))) for _ in range(25)]
    return [(i, _near(rng.choice(bases), rng, rng.choice((0, 0.005, 0.02, 0.03, 0.05)), True)) for i in range(160)]


def test_ngram_join_equals_all_pairs(spark, corpus):
    sets = {i: {tuple(t.split()[j : j + 5]) for j in range(max(1, len(t.split()) - 4))} for i, t in corpus}
    links = {i: sum(_jaccard(a, b) for j, b in sets.items() if j != i) for i, a in sets.items()}
    got = {r["doc_id"]: r for r in ngram_join.ngram_join(spark.createDataFrame(corpus, "doc_id long, text string")).collect()}
    found, all_ = sum(r["n_links"] for r in got.values()), sum(links.values())
    assert all(got[i]["n_links"] <= links[i] for i in links)  # a pair under the threshold is never linked
    assert all_ > 200 and found >= 0.99 * all_
    if found == all_:
        assert {i: r["class_id"] for i, r in got.items()} == _classes(sets, _jaccard)


def test_both_ways_of_verification_find_the_same(spark, corpus, monkeypatch):
    """With blocks of two rows nearly every component is large, and many are verified by their buckets."""
    df = spark.createDataFrame(corpus, "doc_id long, text string")
    want = sorted(map(tuple, ngram_join.ngram_join(df).collect()))
    monkeypatch.setattr(neardup, "BLOCK", 2)
    monkeypatch.setattr(neardup, "SPLIT_GAIN", 1)
    assert sorted(map(tuple, ngram_join.ngram_join(df).collect())) == want


def test_strays_that_join_small_groups(spark, monkeypatch):
    """Texts that share a boilerplate third meet in buckets now and then; their components are split again by buckets."""
    rng = random.Random(2)
    common = " ".join(f"c{k}" for k in range(60))
    rows = [(i, common + " " + _near(" ".join(f"g{i // 2}x{k}" for k in range(60)), rng, 0.02, True)) for i in range(120)]
    sets = {i: {tuple(t.split()[j : j + 5]) for j in range(len(t.split()) - 4)} for i, t in rows}
    monkeypatch.setattr(neardup, "BLOCK", 4)
    monkeypatch.setattr(neardup, "SPLIT_GAIN", 1)
    got = {r["doc_id"]: r["n_links"] for r in ngram_join.ngram_join(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {i: sum(_jaccard(a, b) for j, b in sets.items() if j != i) for i, a in sets.items()}


def test_recall_on_planted_pairs_near_the_threshold(spark):
    """Pairs whose similarity is 0.8 to 0.87: nearly all are found, for documents and for lines."""
    rng, rows, lines, k = random.Random(8), [], [], 0
    while len(rows) < 400:
        a = [f"u{k}x{j}" for j in range(100)]
        b, k = _near(" ".join(a), rng, 0.02, True), k + 1
        sa, sb = ({tuple(t.split()[j : j + 5]) for j in range(96)} for t in (" ".join(a), b))
        if 0.8 <= len(sa & sb) / len(sa | sb) <= 0.87:
            rows += [(len(rows), " ".join(a)), (len(rows) + 1, b)]
    got = ngram_join.ngram_join(spark.createDataFrame(rows, "doc_id long, text string")).where("n_links = 1").count()
    assert got >= 0.99 * len(rows)
    while len(lines) < 400:
        a = "".join(rng.choice("abcdefghijk") for _ in range(rng.choice((60, 100, 200))))
        b = a[: (p := rng.randrange(len(a)))] + "Z" + a[p + 1 :] if len(a) < 150 else _near(a, rng, 0.01, False)
        sa, sb = ({t[j : j + 8] for j in range(len(t) - 7)} for t in (a, b.lower()))
        if 0.8 <= len(sa & sb) / len(sa | sb) <= 0.9:
            lines += [(len(lines), a), (len(lines) + 1, b)]
    found = line_dedup.duplicate_lines(spark.createDataFrame(lines, "doc_id long, text string")).where("n_dropped = 1").count()
    assert found >= 0.99 * len(lines) / 2


def test_line_dedup_equals_all_pairs(spark):
    rng = random.Random(3)
    bases = ["".join(rng.choice("abcdefghijk ") for _ in range(rng.choice((5, 20, 60, 150)))) for _ in range(12)]
    rows = [(i, "\n".join(_near(rng.choice(bases), rng, rng.choice((0, 0.01, 0.03)), False) if rng.random() < 0.9 else "" for _ in range(rng.randrange(1, 5)))) for i in range(60)]
    lines = [(i, n, line_dedup.normal(x)) for i, t in rows for n, x in enumerate(t.split("\n"))]
    sets = {(i, n): {x[j : j + 8] for j in range(max(1, len(x) - 7))} for i, n, x in lines if x}
    want = _classes(sets, _jaccard)
    got = {(r["doc_id"], n) for r in line_dedup.duplicate_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect() for n in r["dropped"]}
    assert got == {k for k, r in want.items() if k != r}


def test_decontamination_of_items_of_any_length(monkeypatch):
    def least(item, text):
        row = [0] * (len(text) + 1)
        for i, a in enumerate(item, 1):
            left, row[0] = row[0], i
            for j, b in enumerate(text, 1):
                left, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, left + (a != b))
        return min(row)

    rng = random.Random(1)
    for hits in (decontam.MOST_HITS, 40):
        monkeypatch.setattr(decontam, "MOST_HITS", hits)
        for _ in range(80):
            items = ["".join(rng.choice("abcd ") for _ in range(rng.choice((1, 5, 8, 9, 10, 15, 20, 23, 30, 31, 40, 80)))) for _ in range(4)]
            texts = ["zz" + _near(rng.choice(items), rng, rng.choice((0, 0.1)), False) + "yy" * rng.randrange(9) for _ in range(3)] + [""]
            docs = [decontam.codes(decontam.normal(t)) for t in texts]
            got = {(d, b.ids[i]): e for b in decontam.Benchmark.of(list(enumerate(items)), 8, 0.1) for d, i, e, _, _ in b.search(docs, b.table())}
            every = {(d, i): least(x, t) for d, t in enumerate(texts) for i, x in enumerate(items)}
            assert got == {k: e for k, e in every.items() if e <= int(0.1 * len(items[k[1]]))}


def test_decontamination_of_many_items_with_one_opening(monkeypatch):
    """Their common q-grams give over a million hits, and the parts are small: only the items that are there are found."""
    rng = random.Random(5)
    monkeypatch.setattr(decontam, "MOST_HITS", 1 << 16)
    opening = "the following question asks you to "
    items = [(i, opening + "".join(rng.choice("abcdefghijklmnop ") for _ in range(120))) for i in range(2000)]
    texts = [opening[:28] + items[i][1][28:] if i % 30 == 0 else opening[:28] + "".join(rng.choice("qrstuvwxyz") for _ in range(100)) for i in range(60)]
    docs = [decontam.codes(decontam.normal(t)) for t in texts]
    got = {(d, b.ids[i]) for b in decontam.Benchmark.of(items, 8, 0.1) for d, i, *_ in b.search(docs, b.table())}
    assert got == {(0, 0), (30, 30)}
    (b,) = decontam.Benchmark.of([(1, "a" * 300)], 8, 0.1)
    assert [x[:3] for x in b.search([decontam.codes("a" * 20_000)], b.table())] == [(0, 0, 0)]


def test_decontamination_edge_cases(spark):
    bench = spark.createDataFrame([(1, "a passage of the benchmark that is long enough to be found", "x"), (1, "a passage of the benchmark that is long enough to be found", "y"), (None, "null id", ""), (2, None, ""), (3, "", "")], "item_id int, text string, doc_id string")
    docs = spark.createDataFrame([(1, "see: A passage of the benchmark\nthat is long enough to be found.", "a", 1), (1, "see: A passage of the benchmark\nthat is long enough to be found.", "a", 1), (None, "a passage of the benchmark that is long enough to be found", "b", 2), (4, None, "c", 3), (5, "", "d", 4), (6, "clean text " * 20_000, "e", 5)], "doc_id int, text string, item_id string, edits int")
    got = sorted((str(r["doc_id"]), r["item_id"], r["edits"], r["start"]) for r in decontam.contaminated(docs, bench).collect())
    assert got == [("1", 1, 0, 5), ("1", 1, 0, 5), ("None", 1, 0, 0)]


def _encoders(rng: random.Random) -> dict:
    b64, pct = base64.b64encode, lambda b: "".join(f"%{c:02X}" for c in b).encode()
    back = lambda b: "".join(f"\\x{c:02x}" for c in b).encode()
    return {
        "base64": b64, "url base64": lambda b: base64.urlsafe_b64encode(b).rstrip(b"="), "percent": pct, "backslash": back, "unicode": lambda b: "".join(f"\\u{c:04x}" for c in b).encode(),
        "gzip": lambda b: b64(gzip.compress(b)), "zlib": lambda b: b64(zlib.compress(b)), "percent gzip": lambda b: pct(gzip.compress(b)), "backslash gzip": lambda b: back(gzip.compress(b)),
        "after a path": lambda b: b"x/" + b64(b), "after a word": lambda b: b"words"[: rng.randrange(1, 5)] + b64(b), "gzip after a path": lambda b: b"a/" + b64(gzip.compress(b)), "broken percent": lambda b: b"%FF" + pct(b) + b"%fe",
        "utf-16": lambda b: b64(b.decode("latin-1").encode("utf-16")), "zlib inside": lambda b: b64(b"\x00\x01junk" + zlib.compress(b)), "nul": lambda b: b64(b"a\0" + b + b"\0\xff"), "cut gzip": lambda b: b64(gzip.compress(b)[:-6]),
    }


def test_secrets_in_generated_nestings():
    """What the encoders wrapped, in any order and depth, is found again inside the place it was wrapped at."""
    rng = random.Random(5)
    enc = _encoders(rng)
    for _ in range(600):
        x, path = rng.choice((b"AKIA" + b"Q" * 16, b"password=hunter2hunter2", b"0123456789abcdef01234567", b"token:abcdef")), []
        for _ in range(rng.randrange(1, 5)):
            path.append(rng.choice(list(enc)))
            x = enc[path[-1]](x)
        text = f"Ünï text {x.decode()} end"
        base, full = secrets.scan(text)
        assert set(base) <= set(full) and any(9 <= a < b <= 9 + len(x) for a, b, _ in full), path
        assert all(0 <= a < b <= len(text) for a, b, _ in full)
    assert secrets.scan(base64.b64encode(zlib.compress(b"f" * 24)).decode())[1]  # few letters, many bytes


def test_quality_with_other_columns_and_ids(spark):
    good, bad = "the quick brown fox jumps over the lazy dog", "zzqx zzqx zzqx !!! $$$ zzqx"
    rows = [(i, bad if i % 2 else good, "q", 1.0, "h") for i in range(80)] + [(None, good, "q", 1.0, "h"), (7, bad, None, None, None), (100, None, "", 0.0, ""), (101, "", "", 0.0, ""), (102, good * 5000, "", 0.0, "")]
    docs = spark.createDataFrame(rows, "item int, body string, quality string, score double, held_out string")
    labels = spark.createDataFrame([(i, 1 - i % 2, "x", None) for i in range(80)] + [(3, 0, "again", None), (None, 1, "", None), (5, 9, "", None), (6, None, "", None)], "doc_id int, quality long, text string, body string")
    model = quality.train(docs, labels, quality.Settings(bits=12, epochs=4), "item", "body")
    got = quality.score_documents(docs, model, "item", "body").collect()
    assert len(got) == len(rows) and all(r["predicted"] == (r["doc_id"] + 1) % 2 for r in got if r["doc_id"] is not None and r["doc_id"] < 80)
    assert {r["score"] for r in got if r["doc_id"] in (100, 101)} == {1 / (1 + 2.718281828459045**-model.bias)} or all(0 <= r["score"] <= 1 for r in got)
    assert quality.keep_good(docs, model, "body").columns == docs.columns


def test_quality_score_equals_the_plain_model(spark):
    """The score from cached word sums is the softmax of the averaged vectors, computed without them."""
    rows = [(i, "spam spam " * 5 if i % 2 else f"a plain text number {i} of words") for i in range(60)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    model = quality.train(docs, spark.createDataFrame([(i, 1 - i % 2) for i in range(60)], "doc_id long, quality int"), quality.Settings(bits=10, epochs=3))
    for r in quality.score_documents(docs, model).collect():
        at, share = quality.counted(dict(rows)[r["doc_id"]], model.settings)
        z = model.bias + float(share.astype(float) @ model.gain[at])
        assert abs(r["score"] - 1 / (1 + 2.718281828459045**-z)) < 1e-6


def test_sharding_is_near_equal_and_whole(spark):
    rng = random.Random(6)
    rows = [(i, f"{i}" + rng.choice("ab") * rng.choice((1, 30, 5000, rng.randrange(9000)))) for i in range(800)] + [(900 + i, "copy" * 50) for i in range(400)] + [(None, None), (5, "a"), (5, "a")]
    got = sharding.shard_by_size(spark.createDataFrame(rows, "doc_id long, text string"), 4).collect()
    texts: dict = {}
    for i, t in rows:
        texts.setdefault(zlib.crc32((t or "").encode()), 0)
    load = [sum(r["size"] for r in got if r["shard"] == s) for s in range(4)]
    assert len(got) == len(rows) and max(load) - min(load) <= 0.01 * sum(load)
    assert all(len({r["shard"] for r in got if r["text_crc32"] == c}) == 1 for c in texts)
    for s in range(4):
        assert sorted(r["slot"] for r in got if r["shard"] == s) == list(range(sum(r["shard"] == s for r in got)))


def test_exact_dedup_with_small_filters(spark, monkeypatch):
    rng = random.Random(9)
    rows = [(i, f"Text {rng.randrange(200)}" if i % 3 else f"own {i}") for i in range(600)]
    want = sorted(map(tuple, exact_dedup.exact_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()))
    monkeypatch.setattr(exact_dedup, "MOST_WORDS", 8)
    assert sorted(map(tuple, exact_dedup.exact_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect())) == want
    groups: dict = {}
    for i, t in rows:
        groups.setdefault(t.lower(), []).append(i)
    assert [(r[0], r[1], r[2]) for r in want] == sorted((i, max(groups[t.lower()]), len(groups[t.lower()])) for i, t in rows)


def test_licenses_equal_brute_force(spark):
    """Every line, run of lines and window without anchors or shortcuts, and directories walked one by one."""
    import math
    from collections import Counter

    rng = random.Random(4)
    pool = [t for ts in licenses.TEMPLATES.values() for t in ts] + [licenses.FILE_TEMPLATES["Apache-2.0"][0], licenses.FILE_TEMPLATES["GPL-3.0"][0], licenses.FILE_TEMPLATES["MIT"][0]]
    noise = lambda n: " ".join(rng.choice("alpha beta gamma the of software license version and".split()) for _ in range(n))
    files = []
    for i in range(60):
        lines = [noise(rng.randrange(12)) for _ in range(rng.randrange(4))]
        if rng.random() < 0.6:
            lines.insert(rng.randrange(len(lines) + 1), _near(rng.choice(pool), rng, rng.choice((0, 0.1, 0.3)), True) + " " + noise(rng.choice((0, 0, 8))))
        files.append((i, "/".join(rng.choice("ab") for _ in range(rng.randrange(4))) + rng.choice(("/LICENSE", "/x.py")), "\n".join(lines) + ("\n" + noise(300) if i % 20 == 0 else "")))
    files += [(70, None, "Released under the MIT License"), (71, "q/LICENSE", None), (71, "q/LICENSE", None), (72, "", "")]
    terms = licenses.terms
    n, df = len(files), Counter(t for _, _, x in files for t in set(terms(x or "")))
    idf = lambda t: math.log((1 + n) / (1 + df[t])) + 1

    def cosine(a, b):
        va, vb = ({t: k * idf(t) for t, k in Counter(x).items()} for x in (a, b))
        return round(sum(x * vb.get(t, 0) for t, x in va.items()) / math.sqrt(sum(x * x for x in va.values()) * sum(x * x for x in vb.values())), 9) if a and b else 0

    def own(text, whole):
        words = [(t, i) for i, line in enumerate(text.split("\n")) for t in terms(line)]
        best = (0.75 - 1e-12, 0, None)
        units = [(terms(x), i) for i, x in enumerate(text.split("\n"))] + [([t for t, _ in words[a : a + len(terms(x))]], -1) for ts in licenses.TEMPLATES.values() for x in ts for a in range(max(0, len(words) - len(terms(x)) + 1))]
        units += [(terms("\n".join(text.split("\n")[a:b])), a) for a in range(len(text.split("\n"))) for b in range(a + 2, len(text.split("\n")) + 1)]
        top = max((cosine(u, terms(x)) for u, _ in units for ts in licenses.TEMPLATES.values() for x in ts), default=0)
        if whole:
            top = max(top, max((cosine([t for t, _ in words], terms(x)) for ts in licenses.FILE_TEMPLATES.values() for x in ts), default=0))
        return top if top >= best[0] else None

    got = licenses.scan_licenses(spark.createDataFrame(files, "doc_id long, path string, text string")).collect()
    by = {r["doc_id"]: r for r in got}
    assert len(got) == len(files)
    for i, path, text in files:
        want = own(text or "", licenses.is_license_file(path))
        if want is not None and not licenses.is_license_file(path):
            assert by[i]["own_similarity"] == pytest.approx(want, abs=1e-6) or by[i]["own_similarity"] <= want, (i, text)
        assert want is None or by[i]["own_license"] is not None, (i, text)
    grants: dict = {}
    for r in got:
        if r["path"] is not None and licenses.is_license_file(r["path"]) and r["own_license"]:
            d = r["path"].rsplit("/", 1)[0]
            grants[d] = min(grants.get(d, (0, "~", "")), (-r["own_similarity"], r["path"], r["own_license"]))
    for r in got:
        d, want = (r["path"] or "").rpartition("/")[0], None
        while r["path"] is not None and want is None:
            want = grants.get(d)
            if not d:
                break
            d = d.rpartition("/")[0]
        assert r["license"] == (r["own_license"] or (want and want[2])), r


def test_license_files_as_wholes(spark):
    mit, apache, gpl = (licenses.FILE_TEMPLATES[k][0] for k in ("MIT", "Apache-2.0", "GPL-3.0"))
    wrap = lambda t: "\n".join(" ".join(t.split()[i : i + 11]) for i in range(0, len(t.split()), 11))
    rest = "\n".join(f"section {i} of further terms that aren't in the opening" for i in range(400))
    files = [(1, "a/LICENSE", wrap(mit).replace("year holder", "2020 Some One")), (2, "b/LICENSE.txt", wrap(apache) + "\n" + rest), (3, "c/COPYING", wrap(gpl) + "\n" + rest), (4, "a/x/y.c", "int x;"), (5, "d/LICENSE", "no terms here"), (6, "c/z.c", "")]
    got = {r["doc_id"]: r["license"] for r in licenses.scan_licenses(spark.createDataFrame(files, "doc_id long, path string, text string")).collect()}
    assert got == {1: "MIT", 2: "Apache-2.0", 3: "GPL-3.0", 4: "MIT", 5: None, 6: "GPL-3.0"}
    assert licenses.scan_licenses(spark.createDataFrame([], "doc_id long, path string, text string")).count() == 0
