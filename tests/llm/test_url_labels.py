"""Statistics of all labelled urls; a hot url doesn't fill the sample."""

from pyspark.sql import functions as F

from erblock.llm import url_filter


def test_all_suffixes_and_a_hot_url(spark):
    n = 1200
    urls = [(f"http://www.site{i}.test{i}/x", i % 2) for i in range(n)]
    df = spark.createDataFrame(urls, "url string, block int")
    hot = df.where("block = 1").orderBy(F.xxhash64("url")).first().url
    df = df.unionByName(spark.createDataFrame([(hot, 1)] * 500, df.schema))
    model = url_filter.fit(df, max_labelled=100, rounds=1, depth=2)
    assert model is not None and model.suffixes.count() == n
    assert model.suffixes.agg(F.max("n"), F.sum("n")).first()[:] == (501, n + 500)


def test_own_label_does_not_leak(spark):
    # Every url has a suffix of its own and labels are chance: nothing can be learnt.
    urls = [(f"http://{i * 7919 % 100_003}.x{i}.test{i}/p", (i * 2654435761 >> 7) % 2) for i in range(3000)]
    found = url_filter.held_out(spark.createDataFrame(urls, "url string, block int"), rounds=3).first()
    assert 500 < found.urls < 700 and abs(found.accuracy - 0.5) < 0.1


def test_held_out_accuracy_where_form_tells(spark):
    urls = [(f"http://a{i}.example{i % 5}.com/" + ("x" * (i % 9) if i % 2 else f"{i * 97}?q={i}&r=2&s=3"), (i + 1) % 2) for i in range(1500)]
    found = url_filter.held_out(spark.createDataFrame(urls, "url string, block int")).first()
    assert found.accuracy > 0.97 > found.majority
    assert url_filter.held_out(spark.createDataFrame([], "url string, block int")).count() == 0


def test_ties_repeats_long_urls_and_clashing_columns(spark):
    long = "http://long.example.net/" + "a/" * 60_000 + "?x=1"
    rows = [(1, "http://org.com/de/x"), (1, "http://org.com/de/x"), (None, "http://ORG/"), (2, long), (3, "://"), (4, "http://.org/"), (5, "")]
    df = spark.createDataFrame([(*r, "h", 1.0, "r") for r in rows], "page_id long, url string, host string, margin double, rule string")
    got = [(r.page_id, r.host, r.rule, r.verdict) for r in url_filter.judge(df).collect()]
    assert got.count((1, "org.com", "com/de/", "block")) == 2 and (None, "org", "org/", "allow") in got
    assert len(got) == 7 and all(r[3] in ("allow", "block") for r in got)
    assert (2, "long.example.net") in [g[:2] for g in got] and (4, ".org", "org/", "allow") in got
