from rangesieve import catalogue, contests

D = "/root/testdata/sf0.001"


class Seen(Exception):
    pass


def test_enhanced_query_asks_every_key(spark, monkeypatch):
    asked = {}

    class Probe:
        def probe(self, queries):
            asked["n"] = queries.count()
            raise Seen

    monkeypatch.setattr(catalogue.EnhancedFilter, "build", lambda keys, **_: asked.update(keys=keys.count()) or Probe())
    try:
        catalogue.queries()["enhanced_no_false_negatives"](spark, D)
    except Seen:
        pass
    assert asked["n"] == asked["keys"] > 0


def test_tuned_query_searches_the_whole_grid(spark, monkeypatch):
    seen = {}

    def build(keys, sample=None, **grid):
        seen.update(grid=grid, n=sample.count())
        raise Seen

    monkeypatch.setattr(contests.baselines.TunedTrieBloom, "build", build)
    try:
        catalogue.queries()["base_tuned_trie_bloom"](spark, D)
    except Seen:
        pass
    keys, sample = catalogue.k.range_queries(catalogue.k.integer_keys(spark, D, "normal"), "same_dist", 1 << 7)
    assert seen == {"grid": {}, "n": sample.count()}
