"""Every operator against a brute-force version on a table with nulls, empty and long texts, ties, repeats and clashing columns."""

import hashlib
import random
import re
import tracemalloc
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from rangesieve.llm import decontamination, line_dedup, mixing, ngram_join, personal_data, quality, secret_scan, sharding, substring_dedup, url_filter

WORD = re.compile(r"[^\x20\x09-\x0D]+")
ALNUM = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
SCHEMA = "doc_id long, text string, source string, lang string, n_words long, size long, shard int, kept boolean, cls string"


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def corpus():
    r = random.Random(7)
    vocabulary = ["".join(r.choice("abcdeéß") for _ in range(r.randrange(1, 7))) for _ in range(300)]
    make = lambda n: " ".join(r.choice(vocabulary) for _ in range(n))
    passage, base, line = make(70), make(200), make(12)
    texts = [None, "", "  \n\t ", "one", "Two words\n\nTwo words", make(20_000), base, base, base.replace(" a", " zz", 1), make(30) + " " + passage + " " + make(40), make(10) + "\n" + passage, passage]
    texts += [f"{make(15)}\n{line}\n{make(25)}" for _ in range(12)]
    texts += [base + " " + make(k) for k in range(1, 12)] + [make(5) for _ in range(6)] + [make(60) for _ in range(20)]
    texts += ["mail a.b@c.de or x@y.zz@q.rr ip 1.2.3.4 999.1.1.1 card 4111 1111 1111 1111 tel +1 (555) 123-4567 é +12 3", 'token = "0123456789abcdef0123" password: secret : abcdefghijklmnop AKIA' + "A" * 20 + " deadbeefdeadbeef"]
    return [(i, t, None if i % 7 == 0 else f"s{i % 3}", "en", 1, 2, 3, True, "x") for i, t in enumerate(texts)] + [(8, texts[8], "s2", "en", 1, 2, 3, True, "x")]


@pytest.fixture(scope="module")
def rows():
    return corpus()


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def test_sharding(docs, rows, none):
    out = sharding.shard_by_bytes(docs, 8).collect()
    assert sorted(r["doc_id"] for r in out) == sorted(r[0] for r in rows)
    largest, whole = max(r["size"] for r in out), sum(r["size"] for r in out)
    for s in range(8):
        mine = [r for r in out if r["shard"] == s]
        assert sorted(r["slot"] for r in mine) == list(range(len(mine)))
        assert abs(sum(r["size"] for r in mine) - whole / 8) <= largest
    ordered = sorted(out, key=lambda r: (r["shard"], r["slot"]))
    assert [r["doc_id"] for r in ordered] == sorted(r["doc_id"] for r in out)
    assert sharding.shard_by_bytes(none, 8).count() == 0


def test_sharding_checksums(spark, tmp_path, rows):
    spark.createDataFrame(rows, SCHEMA).write.parquet(f"{tmp_path}/documents.parquet")
    for r in sharding.op1_sharding(spark, str(tmp_path)).collect():
        text = rows[r["doc_id"]][1] or ""
        assert r["text_crc32"] == zlib.crc32(text.encode()) and r["size"] == len(text.encode()) + 1


def test_substring_dedup(docs, rows, none):
    first, words = {}, {}
    for i, t, *_ in rows:
        words[i] = WORD.findall(t or "")
        for k in range(len(words[i]) - 49):
            first.setdefault(tuple(words[i][k : k + 50]), i)
            first[tuple(words[i][k : k + 50])] = min(first[tuple(words[i][k : k + 50])], i)
    for r in substring_dedup.remove_repeats(docs).collect():
        w = words[r["doc_id"]]
        gone = [False] * len(w)
        for k in range(len(w) - 49):
            if first[tuple(w[k : k + 50])] < r["doc_id"]:
                gone[k : k + 50] = [True] * 50
        kept = " ".join(x for x, g in zip(w, gone, strict=True) if not g)
        assert (r["n_words"], r["n_removed"], r["kept_text"], r["kept_sha256"]) == (len(w), sum(gone), kept, hashlib.sha256(kept.encode()).hexdigest())
    assert substring_dedup.remove_repeats(none).count() == 0


@pytest.mark.parametrize("block_bytes", [1 << 24, 400])
def test_decontamination(spark, docs, rows, none, block_bytes):
    items = [(i, rows[i][1]) for i in (3, 9, 11, 30, 40)] + [(77, None), (78, "one two"), (11, rows[11][1])]
    benchmark = spark.createDataFrame(items, "item_id long, text string")
    windows = {}
    for i, t in items:
        w = ALNUM.findall(lower(t))
        m = min(13, len(w))
        for k in range(len(w) - m + 1 if m else 0):
            windows.setdefault(tuple(w[k : k + m]), set()).add(str(i))
    for r in decontamination.find_contamination(docs, benchmark, block_bytes=block_bytes).collect():
        w = ALNUM.findall(lower(rows[r["doc_id"]][1]))
        hit, found = [0] * len(w), set()
        for m in {len(x) for x in windows}:
            for k in range(len(w) - m + 1):
                if own := windows.get(tuple(w[k : k + m])):
                    hit[k : k + m] = [1] * m
                    found |= own
        assert (r["n_words"], r["n_hit"], r["item_ids"]) == (len(w), sum(hit), sorted(found))
        assert r["contaminated"] == (sum(hit) > 0 and 20 * sum(hit) >= len(w))
    assert decontamination.find_contamination(none, benchmark).count() == 0
    assert decontamination.find_contamination(docs, benchmark.limit(0)).where("contaminated").count() == 0


def test_url_filter(spark):
    page = '<a href="{}">x</a>'
    data = [
        (1, "http://a.net/x", page.format("http://far.org/en/")), (2, "https://B.Example.NET/en/1?q", ""), (3, "http://far.org/en/1", page.format("http://a.net/")), (4, None, None),
        (5, "no scheme", page.format("http://b.example.net/")), (6, "http://x.example.com/de/1", ""), (7, "http://y.org/fr/2#z", page.format("/own")), (8, "http://lone.com", "<a href=>"),
    ]
    out = {r["page_id"]: r for r in url_filter.filter_urls(spark.createDataFrame(data, "page_id long, url string, html string")).collect()}
    assert (out[1]["host"], out[1]["path"], out[1]["rule"], out[1]["verdict"]) == ("a.net", "/x", "net/", "block")
    assert (out[2]["host"], out[2]["rule"], out[2]["verdict"]) == ("b.example.net", "example.net/en/", "allow")
    assert (out[6]["verdict"], out[7]["rule"], out[7]["path"]) == ("block", "org/fr/", "/fr/2")
    # far.org links to a host that the rules block, and nothing trusted links to it
    assert out[3]["rule"] is None and out[3]["verdict"] == "block"
    assert (out[4]["host"], out[4]["path"], out[4]["verdict"], out[8]["verdict"]) == ("", "", "allow", "allow")


def test_few_blocked_pages_seed_distrust(spark):
    data = [(0, "http://m.bad.com/de/1", "")] + [(k, f"http://m.bad.com/x/{k}", "") for k in range(1, 9)] + [(9, "http://fine.com/1", "")]
    pages = spark.createDataFrame(data, "page_id long, url string, html string")
    out = {r["page_id"]: r["verdict"] for r in url_filter.filter_urls(pages, rules=(("block", "com/de/"),)).collect()}
    assert out == {k: "block" for k in range(9)} | {9: "allow"}


def test_rounds_reach_the_tolerance():
    assert 2 * url_filter.DAMPING ** url_filter.rounds_to(url_filter.TOLERANCE) <= url_filter.TOLERANCE


def test_propagation_is_pagerank(spark):
    import numpy as np

    edges = [("a", "b", 2), ("a", "c", 1), ("b", "c", 1), ("c", "a", 1), ("d", "a", 1)]
    seeds = {"a": 0.5, "d": 0.5}
    got = {r["host"]: r["rank"] for r in url_filter.propagate(spark.createDataFrame([("trust", *e) for e in edges], "kind string, src string, dst string, n long"), spark.createDataFrame([("trust", h, s) for h, s in seeds.items()], "kind string, host string, seed double"), rounds=60).collect()}
    names = "abcd"
    m = np.zeros((4, 4))
    for s, t, n in edges:
        m[names.index(t), names.index(s)] = n
    m /= m.sum(axis=0)
    seed = np.array([seeds.get(x, 0.0) for x in names])
    want = np.linalg.solve(np.eye(4) - 0.85 * m, 0.15 * seed)
    assert all(abs(got[x] - want[i]) < 1e-4 for i, x in enumerate(names))


def test_line_dedup(docs, rows, none):
    known = {}
    for i, t, *_ in sorted(set(r[:2] for r in rows), key=lambda x: x[0]):
        for k, text in enumerate((t or "").split("\n")):
            if w := frozenset(WORD.findall(text)):
                known[i, k] = w
    order = sorted(known)
    want = {}
    for n, x in enumerate(order):
        want[x] = any(100 * len(known[x] & known[y]) >= 75 * len(known[x] | known[y]) for y in order[:n])
    got = {(r["doc_id"], r["line"]): r["removed"] for r in line_dedup.find_similar_lines(docs).collect()}
    assert got == want and any(want.values())
    assert line_dedup.find_similar_lines(none).count() == 0


def test_line_dedup_within_a_document_beyond_the_cap(spark):
    data = []
    for x in range(8):
        base = [f"t{x}a{k}" for k in range(40)]
        line = lambda at, new: " ".join(f"{new}{k}" if at <= k < at + 4 else w for k, w in enumerate(base))  # noqa: B023, E731
        # five variants in earlier documents resemble the first line of the sixth, which only the second line resembles
        data += [(10 * x + v, line(4 * v, f"v{x}v{v}n")) for v in range(5)] + [(10 * x + 9, " ".join(base) + "\n" + line(36, f"c{x}n"))]
    sets = {(d, n): frozenset(y.split()) for d, t in data for n, y in enumerate(t.split("\n"))}
    order = sorted(sets)
    want = {y: any(100 * len(sets[y] & sets[z]) >= 75 * len(sets[y] | sets[z]) for z in order[:n]) for n, y in enumerate(order)}
    got = {(r["doc_id"], r["line"]): r["removed"] for r in line_dedup.find_similar_lines(spark.createDataFrame(data, "doc_id long, text string")).collect()}
    assert got == want and all(want[10 * x + 9, 1] for x in range(8))


def test_secret_scan(docs, rows, none):
    kinds = [("assign", re.compile(r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""), lambda m: len(m[2]) >= 12), ("access", re.compile("AKIA[A-Z0-9]+"), lambda m: len(m[0]) >= 18), ("hex", re.compile("[0-9a-f]+"), lambda m: len(m[0]) >= 16)]
    paths, found, added = secret_scan.scan_versions(docs)
    for r in secret_scan.findings_by_path(paths, found).collect():
        want = sorted((m.start(), k, name, m.end()) for k, (name, p, ok) in enumerate(kinds) for m in p.finditer(rows[r["doc_id"]][1] or "") if ok(m))
        assert [(s["start"], s["order"], s["kind"], s["end"]) for s in r["spans"]] == want
    again = secret_scan.scan_versions(docs, ledger=added, findings=found)
    assert again[2].count() == 0 and again[1].count() == found.count() > 0
    assert secret_scan.findings_by_path(*secret_scan.scan_versions(none)[:2]).count() == 0


def test_ngram_join(docs, rows, none):
    sets, up = {}, {}
    for i, t, *_ in rows:
        w = WORD.findall(lower(t))
        sets[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()
        up[i] = i

    def top(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in sets:
        for b in sets:
            if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                x, y = top(a), top(b)
                up[max(x, y)] = min(x, y)
    got = [(r["doc_id"], r["n_shingles"], r["component_id"]) for r in ngram_join.join_ngrams(docs)[0].collect()]
    assert sorted(got) == sorted((i, len(sets[i]), top(i)) for i, *_ in rows)
    assert ngram_join.join_ngrams(none)[0].count() == 0


def test_ngram_join_counts_every_link(spark, monkeypatch):
    monkeypatch.setattr(ngram_join, "BLOCK_MEMBERS", 16)
    r = random.Random(3)
    base = [f"w{k}" for k in range(120)]
    texts = []
    for k in range(70):
        w = list(base)
        for at in r.sample(range(120), r.choice([0, 1, 2, 4])):
            w[at] = f"x{r.randrange(12) if k % 2 else k}y{at}"
        texts.append(" ".join(w))
    texts += [" ".join(f"a{k}b{j}" for j in range(30)) for k in range(8)] + ["", "one", "one"]
    sets = [{tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set() for w in map(str.split, texts)]
    near = lambda a, b: bool(sets[a]) and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])
    n = range(len(texts))
    out, links = ngram_join.join_ngrams(spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string").repartition(3))
    assert {x["doc_id"]: x["n_links"] for x in out.collect()} == {a: sum(near(a, b) for b in n if b != a) for a in n}
    heads = [a for a in n if sets[a] and not any(sets[b] == sets[a] for b in range(a))]
    want = sorted((a, b, len(sets[a] & sets[b]), len(sets[a] | sets[b])) for a in heads for b in heads if a < b and near(a, b))
    assert sorted(map(tuple, links.collect())) == want and len(want) > 6 * len(heads)


def test_more_buckets_make_no_more_candidate_rows(spark, monkeypatch):
    made, real, r = spark.sparkContext.accumulator(0), ngram_join.stars, random.Random(5)

    def counted(group):
        out = real(group)
        made.add(out.num_rows)
        return out

    monkeypatch.setattr(ngram_join, "stars", counted)
    words = [f"w{r.randrange(5000)}" for _ in range(300)]
    texts = [" ".join(words[:k] + [f"x{k}"] + words[k + 1 :]) for k in range(0, 280, 7)]
    data = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    rows, found = [], []
    for shingles in (250, 50):
        before = made.value
        monkeypatch.setattr(ngram_join, "BUCKET_SHINGLES", shingles)
        found.append(sorted(map(tuple, ngram_join.join_ngrams(data)[0].collect())))
        rows.append(made.value - before)
    assert found[0] == found[1] and {f[3:] for f in found[0]} == {(0, 39)}
    assert 0 < rows[1] <= 1.5 * rows[0]


def test_ngram_join_of_versions(spark):
    one, two = (" ".join(f"{c}{k}" for k in range(60)) for c in "ab")
    a, b = (r["t"] for r in spark.createDataFrame([(one,), (two,)], "t string").orderBy(F.xxhash64("t")).collect())
    data = [(5, b), (5, a), (7, b), (9, b + " more")]
    out = ngram_join.join_ngrams(spark.createDataFrame(data, "doc_id long, text string").coalesce(1))[0].collect()
    assert {(r["doc_id"], r["component_id"], r["n_links"]) for r in out} == {(5, 5, 0), (7, 7, 1), (9, 7, 1)}


def test_signatures_meet_whenever_sets_link():
    import numpy as np

    r = random.Random(11)
    for _ in range(300):
        n = r.choice([1, 2, 4, 7, 9, 20, 60, 200, 700])
        a = {r.randrange(1 << 62) for _ in range(n)}
        b = set(a)
        while b and 100 * len(a & (b - {min(b)})) >= 75 * len(a | b) and r.random() < 0.97:
            b.discard(r.choice(sorted(b)))
        while r.random() < 0.9 and 100 * len(a & b) >= 75 * (len(a | b) + 1):
            b.add(r.randrange(1 << 62))
        if not b or 100 * len(a & b) < 75 * len(a | b):
            continue
        h = np.array([*a, *b], dtype=np.uint64)
        row = np.array([0] * len(a) + [1] * len(b))
        sigs, rows = ngram_join.sign(np.array([len(a), len(b)]), row, h, 75, 100, np.ones(len(h), np.int64))
        roles = [{s >> 2: s & 3 for s in sigs[rows == i].tolist()} for i in (0, 1)]
        asks = lambda x, y: any(v & 2 and roles[y].get(s, 0) & 1 for s, v in roles[x].items())
        seen = [{}, {}]
        for s, i in zip(sigs.tolist(), rows.tolist(), strict=True):
            seen[i][s >> 2] = seen[i].get(s >> 2, 0) | s & 3
        roles = seen
        assert asks(0, 1) or asks(1, 0)


def test_quality(docs, rows, none):
    for r in quality.judge_quality(docs).collect():
        t = rows[r["doc_id"]][1] or ""
        w = WORD.findall(t)
        where = {}
        for k in range(len(w) - 7):
            where.setdefault(tuple(w[k : k + 8]), []).append(k)
        hit = {k + j for v in where.values() if len(v) > 1 for k in v for j in range(8)}
        lines = [x for x in t.split("\n") if WORD.search(x)]
        failed = len(w) < 20 or 100 * len(hit) > 30 * len(w)
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"], r["base_failed"]) == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(hit), failed)
    assert quality.judge_quality(none).count() == 0


def test_boilerplate_depletes_documents(spark):
    shared = " ".join(f"b{i}" for i in range(40))
    data = [(i, shared + "\n" + " ".join(f"w{i}x{j}" for j in range(3 if i else 60)), "h") for i in range(40)]
    out = {r["doc_id"]: r for r in quality.judge_quality(spark.createDataFrame(data, "doc_id long, text string, source string"), share=0.5).collect()}
    assert out[0]["kept"] and not out[1]["kept"] and out[1]["n_removed_words"] == 40


def test_cleaned_texts_lose_boilerplate(spark):
    own = lambda i: " ".join(f"w{i}x{j}" for j in range(60))
    data = [(i, f"Share  this page\n\n{own(i)}\nshare this PAGE", "h") for i in range(40)] + [(50, f"Share this page\n{own(50)}", None)]
    docs = spark.createDataFrame(data, "doc_id long, text string, source string")
    out = {r["doc_id"]: r["text"] for r in quality.cleaned(docs).collect()}
    assert out == {i: f"\n{own(i)}" for i in range(40)} | {50: data[-1][1]}


def test_quality_kernels_hold_little_at_once():
    texts = [" ".join(f"w{(7 * i + k) % 5000}" for k in range(300)) + "\nlast line" for i in range(2500)]
    n = np.arange(len(texts))
    batch = pa.RecordBatch.from_arrays([*(pa.array(x) for x in (n, ["a"] * len(n), n, n)), pa.array(texts)], names=["_id", "_host", "_text_hash", "_row", "text"])
    assert batch.nbytes > 3 << 20
    tracemalloc.start()
    found = pa.Table.from_batches(b.select(["_row", "n_words"]) for b in quality.measure(iter([batch])))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert found["n_words"].to_pylist() == [302] * len(n) and found["_row"].to_pylist() == n.tolist()
    # slices of 2 MB took 124 MB
    assert peak < 60 << 20
    gone = quality.measure(iter([batch.slice(0, 1)])).__next__().column("_lines")[0].as_py()
    lines = pa.array([None if k % 2 else gone for k in n.tolist()], pa.list_(pa.int64()))
    given = pa.RecordBatch.from_arrays([batch.column("_id"), batch.column("text"), lines], names=["doc_id", "text", "lines"])
    parts = list(quality.clean_texts(iter([given])))
    assert max(p.num_rows for p in parts) <= 1000
    kept = [x for p in parts for x in p.column("text").to_pylist()]
    assert [x for p in parts for x in p.column("doc_id").to_pylist()] == n.tolist() and kept[1::2] == texts[1::2] and kept[0] == ""


def test_mixing(docs, rows, none):
    out, quotas = mixing.mix_sources(docs, seats=500)
    got = out.select("doc_id", "source", F.col("size"), "source_size", "target", "taken").collect()
    assert len(got) == len(rows)
    total = sum(len(WORD.findall(r[1] or "")) for r in rows)
    assert abs(sum({r["source"]: r["target"] for r in got}.values()) - 1.5 * total) < 1e-6
    for s in {r["source"] for r in got}:
        mine = [r for r in got if r["source"] == s]
        assert abs(sum(r["taken"] for r in mine) - mine[0]["target"]) <= 2 * 1.5 * total / 500
    assert all(r["size"] == len(WORD.findall(rows[r["doc_id"]][1] or "")) and 0 <= r["taken"] <= 2 * r["size"] for r in got)
    assert quotas.agg(F.sum("blocks")).first()[0] >= 500
    assert mixing.mix_sources(none)[0].count() == 0


def test_tiny_source_beside_a_hot_one(spark):
    data = [(k, " ".join(["w"] * 1000), "hot") for k in range(400)] + [(500 + k, "a b c d e", "tiny") for k in range(4)] + [(600, "a b c d", None)]
    got = mixing.mix_sources(spark.createDataFrame(data, "doc_id long, text string, source string"), seats=200)[0].collect()
    for s in ("hot", "tiny", None):
        mine = [r for r in got if r["source"] == s]
        assert mine[0]["target"] > 0 and abs(sum(r["taken"] for r in mine) - mine[0]["target"]) <= 0.05 * mine[0]["target"] + 1


def test_apportionment_follows_highest_quotients():
    targets = {"a": 53.0, "b": 24.0, "c": 23.0}
    out = mixing.apportion(targets, 10, 4)
    # 53, 24, 23, 53/3, 53/5, 24/3, 23/3, 53/7, 53/9, 53/11 are the highest quotients, in this order
    assert {s: sum(v) for s, v in out.items()} == {"a": 6, "b": 2, "c": 2} and [sum(v[k] for v in out.values()) for k in range(4)] == [3, 3, 2, 2]


def test_personal_data(docs, rows, none):
    def luhn(s):
        d = re.sub("[^0-9]", "", s)
        return 16 <= len(d) <= 19 and sum(int(c) if i % 2 == 0 else 2 * int(c) - 9 * (int(c) > 4) for i, c in enumerate(d[::-1])) % 10 == 0

    kinds = [
        ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda m: True), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: all(int(x) <= 255 for x in m[0].split("."))),
        ("card", r"[0-9]([\x20-]?[0-9])+", lambda m: luhn(m[0])), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 8 <= len(re.sub("[^0-9]", "", m[0])) <= 15),
    ]
    n = 0
    for r in personal_data.find_personal_data(docs).collect():
        want = sorted((m.start(), m.end(), name) for name, p, ok in kinds for m in re.finditer(p, rows[r["doc_id"]][1] or "") if ok(m))
        assert sorted((s["start"], s["end"], s["kind"]) for s in r["base"]) == want
        n += len(want)
    assert n >= 4 and personal_data.find_personal_data(none).count() == 0


def test_loose_personal_data_is_added(spark):
    r = random.Random(2)

    def account():
        body = "".join(r.choice("0123456789") for _ in range(18))
        return f"DE{98 - int(body + '131400') % 97:02d}{body}"

    number = lambda *sizes: ["".join(r.choice("123456789") for _ in range(k)) for k in sizes]
    ident = lambda: f"{r.randrange(100, 600)}-{'-'.join(number(2, 4))}"
    data = []
    for k in range(240):
        # some say what they are, the last ones don't
        said = k < 200
        data += [(4 * k, "ssn " * said + ident()), (4 * k + 1, f"pay {account()} now"), (4 * k + 2, f"write joe{k} [at] mail{k} [dot] org"), (4 * k + 3, ("order " if said else "saw ") + number(12)[0])]
    got = {x["doc_id"]: [s["kind"] for s in x["extra"]] for x in personal_data.find_personal_data(spark.createDataFrame(data, "doc_id long, text string")).collect()}
    for k in range(240):
        assert "ident" in got[4 * k] and got[4 * k + 1] == ["account"] and got[4 * k + 2] == ["spelled"] and not got[4 * k + 3], k


def test_every_labelled_candidate_is_fitted(spark, monkeypatch):
    r, seen, real = random.Random(3), [], personal_data.fitted
    monkeypatch.setattr(personal_data, "fitted", lambda cells: seen.extend(cells) or real(cells))
    accounts = [f"DE{r.randrange(10, 99)}{r.randrange(10**17, 10**18)}" for _ in range(5000)]
    data = [(k, "pay " + " or ".join(accounts[50 * k : 50 * k + 50])) for k in range(100)] + [(100 + k, f"{k}.1.1.1 and {k}.1.1.999") for k in range(250)]
    personal_data.find_personal_data(spark.createDataFrame(data, "doc_id long, text string"))
    number = lambda kind: sum(c[4] for c in seen if c[3][-1] == 1 + personal_data.KINDS.index(kind))
    # the digits of an account are a card's candidate too
    assert (number("account"), number("card"), number("ip")) == (5000, 5000, 500) and len(seen) < 200


def test_counted_rows_boost_as_repeated_ones():
    r = random.Random(6)
    x = [[float(r.randrange(5)), float(r.randrange(4))] for _ in range(60)]
    y, n = [int(a + b > 4) ^ (r.random() < 0.1) for a, b in x], [r.randrange(1, 9) for _ in x]
    much = lambda rows: [v for v, k in zip(rows, n, strict=True) for _ in range(k)]
    (a, counted), (b, repeated) = personal_data.boost(x, y, count=n), personal_data.boost(much(x), much(y))
    assert a == pytest.approx(b) and len(counted) == len(repeated)
    assert [a + sum(t.value(v) for t in counted) for v in x] == pytest.approx([b + sum(t.value(v) for t in repeated) for v in x], abs=1e-6)
    scores = [a + sum(t.value(v) for t in counted) for v in x]
    assert personal_data.calibrated(scores, y, 0.9, n) == personal_data.calibrated(much(scores), much(y), 0.9)


def test_boosting_separates():
    r = random.Random(5)
    x = [[r.random(), r.random(), float(r.randrange(3))] for _ in range(400)]
    y = [int((a > 0.5) != (b > 0.5)) for a, b, _ in x]
    start, trees = personal_data.boost(x, y)
    right = sum((start + sum(t.value(v) for t in trees) > 0) == bool(t_) for v, t_ in zip(x, y, strict=True))
    assert right >= 340
