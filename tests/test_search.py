"""Compilations hold every place of a word or passage, not only the first of each text."""

from collections import Counter

from reelspark.workloads import search


def test_every_place_of_a_passage(spark):
    texts = spark.createDataFrame([(1, "one two one two one"), (2, "aaaa"), (3, "two"), (4, None)], "doc_id bigint, text string")
    passages = spark.createDataFrame([(7, "one"), (8, "aa"), (9, "one two one")], "item_id bigint, text string")
    out = {(r["doc_id"], r["item_id"], r["at"]) for r in search.containing(texts, passages).collect()}
    assert out == {(1, 7, 0), (1, 7, 8), (1, 7, 16), (1, 9, 0), (1, 9, 8), (2, 8, 0), (2, 8, 1), (2, 8, 2)}
    apart = {(r["doc_id"], r["item_id"], r["at"]) for r in search.containing(texts, passages, apart=True).collect()}
    assert apart == {(1, 7, 0), (1, 7, 8), (1, 7, 16), (1, 9, 0), (2, 8, 0), (2, 8, 2)}
    before, search.PASSAGES = search.PASSAGES, 1
    try:
        assert {(r["doc_id"], r["item_id"], r["at"]) for r in search.containing(texts, passages).collect()} == out
    finally:
        search.PASSAGES = before


def test_every_spoken_word_gets_a_clip(spark, sf_dir):
    texts = [(r["doc_id"], r["text"].lower()) for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()]
    want = Counter({d: t.count(search.WORD) for d, t in texts if search.WORD in t})
    assert max(want.values()) > 1
    rows = search.w_search(spark, sf_dir).collect()
    assert Counter(r["doc_id"] for r in rows) == want and sorted(r["occ"] for r in rows) == list(range(1, len(rows) + 1))
    assert search.w_search_spec(spark, sf_dir).count() == sum(r["n"] for r in rows)


def test_no_window_carries_a_text(spark, sf_dir):
    plan = search.w_search(spark, sf_dir)._jdf.queryExecution().optimizedPlan().toString()
    for line in plan.splitlines():
        assert not ("Window [" in line and "text#" in line.replace("stamp_text#", "")), line


def test_running_sums_in_blocks(spark):
    import random

    from reelspark.operators.running import numbered, running

    rng = random.Random(3)
    rows = [(rng.choice(["a", "b", None]), i, rng.randint(-5, 9)) for i in rng.sample(range(1000), 300)] + [("c", None, 4), ("c", 7, 1)]
    df = spark.createDataFrame(rows, "k string, at bigint, v bigint")
    want, count = {}, {}
    for k, at, _ in rows:
        mine = [(a if a is not None else -1, v) for x, a, v in rows if x == k]
        want[k, at] = (sum(v for a, v in mine if a < (at if at is not None else -1)), sum(v for _, v in mine), max((a for a, _ in mine), default=None))
        count[k, at] = sum(a < (at if at is not None else -1) for a, _ in mine)
    for block in (1, 16, 10**6):
        got = running(df, ["k"], "at", "v", "before", block, whole={"sum": "all", "last": "last"}).collect()
        assert len(got) == len(rows) and {(r["k"], r["at"]): (r["before"], r["all"], r["last"]) for r in got} == want
        assert {(r["k"], r["at"]): r["n"] for r in numbered(df, ["k"], "at", "n", block).collect()} == count


def test_found_places_leave_a_task_in_bounded_batches(spark):
    """A batch of texts may hold any number of places."""
    from reelspark.workloads import search

    n = search.PLACES * 2 + 7
    texts = spark.createDataFrame([(1, "a" * n), (2, None), (3, "ba")], "doc_id bigint, text string").coalesce(1)
    found = search.containing(texts, spark.createDataFrame([(7, "a")], "item_id bigint, text string"))
    sizes = found.mapInArrow(lambda it: (b.slice(0, 0).from_pydict({"n": [b.num_rows]}) for b in it), "n bigint")
    assert found.count() == n + 1 and found.where("doc_id = 3 and at = 1").count() == 1
    seen = [r["n"] for r in sizes.collect()]
    assert sum(seen) == n + 1
