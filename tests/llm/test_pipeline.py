"""The first three stages against brute force, the last two by their laws, each on what the stage before kept."""

import re

import corpus_pipeline

D = "/root/testdata/sf0.001"
WORD = re.compile(r"[^\x20\x09-\x0D]+")
ALNUM = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def good(text):
    w, where = WORD.findall(text or ""), {}
    for k in range(len(w) - 7):
        where.setdefault(tuple(w[k : k + 8]), []).append(k)
    hit = {k + j for v in where.values() if len(v) > 1 for k in v for j in range(8)}
    return len(w) >= 20 and 100 * len(hit) <= 30 * len(w)


def test_pipeline(spark):
    docs = spark.read.parquet(f"{D}/documents.parquet")
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    kept = [i for i, t in sorted(texts.items()) if good(t)]
    sets, up = {}, {i: i for i in kept}
    for i in kept:
        w = WORD.findall(lower(texts[i]))
        sets[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)}

    def top(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in kept:
        for b in kept:
            if a < b and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                x, y = top(a), top(b)
                up[max(x, y)] = min(x, y)
    single = [i for i in kept if top(i) == i]
    windows = set()
    for r in spark.read.parquet(f"{D}/benchmark.parquet").collect():
        w = ALNUM.findall(lower(r["text"]))
        windows |= {tuple(w[k : k + min(13, len(w))]) for k in range(len(w) - min(13, len(w)) + 1)}

    def clean(text):
        w = ALNUM.findall(lower(text))
        hit = {k + j for m in {len(x) for x in windows} for k in range(len(w) - m + 1) if tuple(w[k : k + m]) in windows for j in range(m)}
        return not hit or 20 * len(hit) < len(w)

    want = [kept, single, [i for i in single if clean(texts[i])]]
    columns = docs.columns
    for (name, stage), ids in zip(corpus_pipeline.STAGES, want, strict=False):
        docs = stage(spark, docs, D)
        assert docs.columns == columns and sorted(r["doc_id"] for r in docs.select("doc_id").collect()) == ids, name
        docs = spark.createDataFrame(docs.collect(), docs.schema)
    mixed = corpus_pipeline.STAGES[3][1](spark, docs, D)
    copies = {}
    for r in mixed.select("doc_id").collect():
        copies[r["doc_id"]] = copies.get(r["doc_id"], 0) + 1
    assert set(copies) <= set(want[2]) and max(copies.values()) <= 2
    out = corpus_pipeline.STAGES[4][1](spark, mixed, D).collect()
    assert len(out) == sum(copies.values()) and {r["shard"] for r in out} == set(range(8))
