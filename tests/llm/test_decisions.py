"""What the methods decide, against brute force: verdicts of hosts, kept documents, words taken, added spans, cleaned texts, ledgers."""

import dataclasses
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from rangesieve.llm import decontamination, line_dedup, mixing, ngram_join, personal_data, quality, secret_scan, sharding, substring_dedup, url_filter
from rangesieve.llm.oracles import ORACLES

WORD = re.compile(r"[^\x20\x09-\x0D]+")
D = "/root/testdata/sf0.001"


def ranked(hosts, links, seeds, damping=0.85):
    place = {h: i for i, h in enumerate(hosts)}
    m, s = np.zeros((len(hosts), len(hosts))), np.array([seeds.get(h, 0.0) for h in hosts])
    if not s.sum():
        return dict.fromkeys(hosts, 0.0)
    s /= s.sum()
    for (a, b), n in links.items():
        m[place[b], place[a]] += n
    out = m.sum(axis=0)
    m[:, out > 0] /= out[out > 0]
    x = s.copy()
    for _ in range(400):
        inflow = m @ x
        x = s * (1 - damping * inflow.sum()) + damping * inflow
    return dict(zip(hosts, x, strict=True))


def test_host_verdicts_by_brute_force(spark):
    r = random.Random(4)
    hosts = [f"h{i}.{t}" for i, t in enumerate(["org", "net", "com", "example.com", "example.net"] * 4)] + ["lone.com"]
    data, links, rules = [], {}, url_filter.RULES
    for i in range(160):
        src = r.choice(hosts[:-1]) if i else "lone.com"
        path = r.choice(["/fr/1", "/en/2", "/de/3", "/x"])
        hrefs = [] if not i else [f"{r.choice(['http://', 'https://', '//'])}{r.choice(hosts)}/p" for _ in range(r.randrange(4))] + ["/own"]
        data.append((i, f"http://{src}{path}", "".join(f'<a class="k" href="{u}">t</a>' for u in hrefs)))
        for u in hrefs:
            dst = u.split("//")[1].split("/")[0] if "//" in u else src
            if dst != src:
                links[src, dst] = links.get((src, dst), 0) + 1

    def rule(host, path):
        fits = [(len(x), x, v) for v, x in rules for name, _, start in [x.partition("/")] if (host == name or host.endswith("." + name)) and path.startswith("/" + start)]
        return max(fits)[1:] if fits else (None, None)

    host = lambda u: u.split("://")[1].split("/")[0]
    judged = {i: rule(host(u), u.split(host(u))[1]) for i, u, _ in data}
    share = lambda v: {h: sum(judged[i][1] == v for i, u, _ in data if host(u) == h) / n for h in hosts if (n := sum(host(u) == h for _, u, _ in data))}
    trust, distrust = ranked(hosts, links, share("allow")), ranked(hosts, {(b, a): n for (a, b), n in links.items()}, share("block"))
    want = {}
    for i, u, _ in data:
        t, x = trust[host(u)], distrust[host(u)]
        want[i] = (judged[i][0], judged[i][1] or ("block" if x > 0 and x > 0.5 * (t + x) else "allow"))
    out = url_filter.filter_urls(spark.createDataFrame(data, "page_id long, url string, html string").withColumn("rule", F.lit("given")))
    assert {r["page_id"]: (r["rule"], r["verdict"]) for r in out.collect()} == want and {v for r, v in want.values() if r is None} == {"allow", "block"}
    assert url_filter.filter_urls(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_kept_documents_by_brute_force(spark):
    r = random.Random(6)
    word = lambda: f"w{r.randrange(4000)}"
    lines = [" ".join(word() for _ in range(n)) for n in (3, 12, 40)]
    data = []
    for i in range(90):
        body = "\n".join(" ".join(word() for _ in range(r.randrange(1, 14))) for _ in range(r.randrange(1, 6)))
        extra = [x.upper() if r.random() < 0.2 else x for x in lines if r.random() < 0.5]
        data.append((i, "\n".join([*extra, body]), r.choice(["a", "b", None]), 7))
    data += [(100, None, "a", 7), (101, data[0][1], data[0][2], 7), (None, data[1][1], "b", 7)]
    norm = lambda x: " ".join(WORD.findall(x)).translate(str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)}))
    texts = {h: {t or "" for _, t, s, _ in data if s == h} for h in ("a", "b", None)}
    count = lambda h, n: sum(any(norm(x) == n for x in t.split("\n")) for t in texts[h])
    want = {}
    for i, t, h, _ in data:
        own = [x for x in (t or "").split("\n") if WORD.search(x)]
        n = len(WORD.findall(t or ""))
        gone = sum(len(WORD.findall(x)) for x in own if count(h, norm(x)) > 8 and count(h, norm(x)) > 0.3 * len(texts[h]))
        want[i] = (gone, n >= 20 and not (gone and (n - gone < 20 or n - gone < 0.3 * n)))
    out = quality.judge_quality(spark.createDataFrame(data, "doc_id long, text string, source string, _row int").repartition(3), min_texts=8, share=0.3)
    assert {x["doc_id"]: (x["n_removed_words"], x["kept"]) for x in out.collect()} == want
    assert len({k for _, k in want.values()}) == 2 and any(g for g, _ in want.values())


def test_words_taken_by_brute_force(spark):
    r = random.Random(8)
    data = [(i % 150, "x " * r.randrange(0, 40), r.choice(["a", "b", "c", None]), "t") for i in range(160)] + [(7, "y " * 9, "a", "t")] * 3 + [(None, "z z z", "b", "t"), (900, None, "a", "t")]
    docs = spark.createDataFrame(data, "doc_id long, text string, source string, taken string").repartition(4)
    out, quotas = mixing.mix_sources(docs, n_shards=3, seats=100)
    order = docs.select("doc_id", "text", "source", F.xxhash64(F.lit(17), "doc_id", mixing.word_count()).alias("at"), F.xxhash64("doc_id", "text", mixing.word_count()).alias("tie")).collect()
    blocks = {}
    for q in quotas.collect():
        blocks.setdefault(q["source"], {})[q["shard"]] = q["blocks"] * q["block_tokens"]
    got = {}
    for x in out.collect():
        got.setdefault((x["source"], x["doc_id"], x["size"]), []).append((x["taken"], x["shard_taken"]))
    for s in ("a", "b", "c", None):
        mine = sorted((x["at"], x["tie"], x["doc_id"], len(WORD.findall(x["text"] or ""))) for x in order if x["source"] == s and x["doc_id"] is not None or x["source"] == s)
        whole = sum(m[3] for m in mine)
        ends, at = [], 0
        for k in range(3):
            at += blocks[s][k]
            ends.append(min(at, 2 * whole))
        begin, groups = 0, {}
        for m in mine:
            groups.setdefault(m[:2], []).append(m)
        for key in sorted(groups):
            rows = groups[key]
            size, doc = rows[0][3], rows[0][2]
            upto = [e // whole * size + min(size, max(0, e % whole - begin) // len(rows)) if len(rows) > 1 else e // whole * size + min(size, max(0, e % whole - begin)) for e in ends]
            want = [b - a for a, b in zip([0, *upto], upto, strict=False)]
            assert got[s, doc, size] == [(upto[-1], want)] * len(got[s, doc, size]), (s, doc)
            begin += size * len(rows)


def test_ledger_of_an_earlier_version(spark):
    docs = spark.createDataFrame([(1, "token = abcdefghijklmnop"), (2, "AKIA" + "B" * 20), (3, "token = abcdefghijklmnop"), (4, None)], "doc_id long, text string").withColumn("spans", F.lit("given")).withColumn("blob", F.lit(0))
    paths, found, added = secret_scan.scan_versions(docs)
    full = secret_scan.findings_by_path(paths, found)
    assert {r["doc_id"]: len(r["spans"]) for r in full.collect()} == {1: 1, 2: 1, 3: 1, 4: 0}
    newer = tuple(dataclasses.replace(r, version=2) if r.name == "access" else r for r in secret_scan.RULES)
    _, again, due = secret_scan.scan_versions(docs, ledger=added, findings=found, rules=newer)
    # three blobs, for the one rule that changed
    assert {(r["rule"], r["version"]) for r in due.collect()} == {("access", 2)} and due.count() == 3
    assert sorted((r["rule"], r["version"]) for r in again.collect()) == [("access", 2), ("assign", 1)]


def test_personal_data_beside_strict_matches(spark):
    r = random.Random(9)

    def card(valid):
        body = "".join(r.choice("0123456789") for _ in range(15))
        total = sum(int(c) if i % 2 else 2 * int(c) - 9 * (int(c) > 4) for i, c in enumerate(body[::-1]))
        return body + str((-total + (0 if valid else r.randrange(1, 10))) % 10)

    phone = lambda: f"+1 ({r.randrange(100, 999)}) 555-{r.randrange(1000, 9999)}"
    data, planted = [], {}
    for k in range(300):
        a, b = card(True), card(False)
        kind = k % 4
        text = [f"word {a} word", f"word {b} word", f"word {a} {card(True)} word", f"word {phone()} 203.0.113.7 10.20.30.40 word"][kind]
        data.append((k, text))
        planted[k] = {0: [], 1: [], 2: [(5, 21), (22, 38)], 3: [(5, 22)]}[kind]
    hit = wrong = 0
    for x in personal_data.find_personal_data(spark.createDataFrame(data, "doc_id long, text string")).collect():
        every = {(s["start"], s["end"]) for s in x["extra"]}
        hit += len(every & set(planted[x["doc_id"]]))
        wrong += sum(not any(a < e and s < b for a, b in planted[x["doc_id"]]) for s, e in every)
        assert [(s["order"], s["start"]) for s in x["base"]] == sorted((s["order"], s["start"]) for s in x["base"])
    total = sum(map(len, planted.values()))
    assert hit >= 0.9 * total and wrong <= 0.1 * total


def test_redacted_texts(spark):
    docs = spark.createDataFrame([(1, "mail a.b@c.de now"), (2, None), (3, "é 1.2.3.4"), (4, "plain")], "doc_id long, text string")
    assert {r["doc_id"]: r["text"] for r in personal_data.redacted(docs, "#").collect()} == {1: "mail " + "#" * 8 + " now", 2: None, 3: "é " + "#" * 7, 4: "plain"}


def test_texts_without_similar_lines(spark):
    docs = spark.createDataFrame([(1, "a b c d e f g h\nown line here"), (2, "x y\na b c d e f g z\n\nother text"), (3, None), (None, "a b c d e f g h")], "doc_id long, text string")
    out = {r["doc_id"]: r["text"] for r in line_dedup.without_similar_lines(docs).collect()}
    assert out == {1: "a b c d e f g h\nown line here", 2: "x y\n\nother text", 3: None, None: "a b c d e f g h"}


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_sql(spark, name):
    import duckdb

    from rangesieve.llm import queries

    con = duckdb.connect()
    for t in ("documents", "benchmark", "pages"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{D}/{t}.parquet'")
    want = con.execute(ORACLES[name])
    columns = [c[0] for c in want.description]
    got = queries.queries()[name](spark, D)
    assert sorted(columns) == sorted(got.columns)
    assert sorted(map(tuple, got.select(*columns).collect())) == sorted(want.fetchall())


def test_clashing_names_and_rows_without_id(spark):
    """Columns named like helpers and results, rows without doc_id, and versions of one doc_id."""
    text = " ".join(f"w{k}" for k in range(80))
    clash = ("size", "shard", "slot", "taken", "target", "source_size", "n_words", "n_hit", "items", "kept", "base", "extra", "spans", "blob", "class_id", "component_id", "lines", "removed", "host", "_at")
    rows = [(1, text, "a"), (2, text, "b"), (2, text + " more", "b"), (None, text, None), (None, None, "a"), (3, "", "a")]
    docs = spark.createDataFrame([(*r, *range(len(clash))) for r in rows], "doc_id long, text string, source string, " + ", ".join(f"{c} int" for c in clash)).repartition(2)
    items = spark.createDataFrame([(1, text), (None, "w1 w2 w3")], "item_id long, text string")
    outs = [sharding.shard_by_bytes(docs, 8), substring_dedup.remove_repeats(docs), decontamination.find_contamination(docs, items), secret_scan.findings_by_path(*secret_scan.scan_versions(docs)[:2]), quality.judge_quality(docs), mixing.mix_sources(docs, seats=10)[0], personal_data.find_personal_data(docs), ngram_join.join_ngrams(docs)[0]]
    for out in outs:
        assert out.count() == len(rows)
    assert mixing.mixed(docs, seats=10).columns == docs.columns and quality.cleaned(docs).columns == docs.columns and ngram_join.keep_one(docs).columns == docs.columns
    hits = {r["n_hit"] for r in outs[2].where("doc_id = 1").collect()}
    assert hits == {80}


def test_sharding_of_string_keys_and_repeated_keys(spark):
    docs = spark.createDataFrame([("k" if i % 2 else f"x{i}", f"{i} " * 50) for i in range(400)] + [(None, "n")], "name string, text string").repartition(3)
    out = sharding.shard_by_bytes(docs, 4, key="name").collect()
    whole = sum(r["size"] for r in out)
    for s in range(4):
        mine = sorted(r["slot"] for r in out if r["shard"] == s)
        assert mine == list(range(len(mine))) and abs(sum(r["size"] for r in out if r["shard"] == s) - whole / 4) <= 400
    names = [r["name"] for r in sorted(out, key=lambda r: (r["shard"], r["slot"]))]
    assert names[0] is None and names[1:] == sorted(names[1:])
