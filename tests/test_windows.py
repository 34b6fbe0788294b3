"""Window methods: the nine-entity example, brute force over random layouts, and edge cases."""

import random

import pytest
from pyspark.sql import functions as F

from nearsort.operators import layout, measures, methods, pairs, partitioners as parts
from nearsort.plans.resolve import SnConfig, candidates

NINE = [("a", 1, 0), ("b", 2, 0), ("c", 3, 0), ("d", 1, 1), ("e", 2, 1), ("f", 2, 1), ("g", 3, 2), ("h", 2, 2), ("i", 3, 2)]
ALL = set("ad ab db de be bf ef eh fh fc hc hg cg ci gi".split())


@pytest.fixture(scope="module")
def nine(spark):
    return spark.createDataFrame(NINE, "id string, k int, mapper_id int").cache()


def names(df):
    got = [r.left_id + r.right_id for r in df.collect()]
    assert len(got) == len(set(got))
    return set(got)


def test_nine_entities(nine):
    p = parts.cut_partitioner([2])
    assert names(methods.sequential_pairs(nine, 3)) == ALL
    assert names(methods.local_pairs(nine, 3, p)) == ALL - {"fc", "hc", "hg"}
    assert names(methods.stitch_pairs(nine, 3, p)) == ALL
    assert names(methods.replica_pairs(nine, 3, p)) == ALL
    for scope in ("map", "partition"):
        assert names(methods.replica_pairs(nine, 3, p, "adjacent", scope)) == ALL
    boundary = methods.boundary_rows(layout.ordered(nine, p), layout.partition_offsets(layout.tag(nine, p)), 3)
    assert {r.id for r in boundary.collect()} == set("fhcg")
    assert names(methods.seam_pairs(boundary, 3)) == {"fc", "hc", "hg"}
    assert {(r.mapper_id, r.id) for r in methods.replica_rows(nine, 3, p, "map").collect()} == {(0, "a"), (0, "b"), (1, "e"), (1, "f"), (2, "h")}
    assert methods.block_pairs(nine).count() == 10
    assert methods.block_pairs(nine, tile=2).count() == 10


def brute(rows, w):
    order = sorted(rows, key=lambda r: (r[1], r[0]))
    return {(order[i][0], order[j][0], j - i) for i in range(len(order)) for j in range(i + 1, min(len(order), i + w))}


def triples(df):
    got = [(r.left_id, r.right_id, r.distance) for r in df.collect()]
    assert len(got) == len(set(got))
    return set(got)


@pytest.mark.parametrize("seed", range(4))
def test_random_layouts(spark, seed):
    rnd = random.Random(seed)
    rows = [(i, rnd.choice("abcdefgh"), i % 3) for i in range(rnd.choice([1, 9, 40]))]
    e = spark.createDataFrame(rows, "id long, k string, mapper_id int")
    p = parts.cut_partitioner(sorted(rnd.sample("abcdefgh", rnd.randint(0, 5))))
    w = rnd.choice([2, 3, 6, 50])
    want = brute(rows, w)
    for got in (methods.sequential_pairs(e, w), methods.stitch_pairs(e, w, p), methods.replica_pairs(e, w, p), methods.rank_bucket_pairs(e, w, 4), methods.exploded_window_pairs(e, w)):
        assert triples(got) == want


def test_thin_partitions(spark):
    rows = [(i, "aaabcccc"[i], 0) for i in range(8)]
    e = spark.createDataFrame(rows, "id long, k string, mapper_id int")
    p = parts.cut_partitioner(["a", "b"])
    want = brute(rows, 4)
    assert len(want) == 18
    assert triples(methods.stitch_pairs(e, 4, p)) == triples(methods.replica_pairs(e, 4, p)) == want
    lost = {(a, b) for a, b, _ in want - triples(methods.stitch_pairs(e, 4, p, "adjacent"))}
    assert lost == {(1, 4), (2, 4), (2, 5)}


@pytest.mark.parametrize("engine", ["frame", "lag", "ring", "grouped"])
def test_engines_agree(spark, data, engine):
    from nearsort.sources import tables

    e = tables.keyed(spark, data)
    p = parts.balanced_partitioner(e, 5)
    assert triples(methods.local_pairs(e, 5, p, engine=engine)) == triples(pairs.frame(layout.tag(e, p), 5))


def test_empty_and_null(spark):
    e = spark.createDataFrame([], "id long, k string, mapper_id int")
    p = parts.cut_partitioner(["m"])
    for got in (methods.sequential_pairs(e, 3), methods.stitch_pairs(e, 3, p), methods.replica_pairs(e, 3, p), methods.rank_bucket_pairs(e, 3, 2)):
        assert got.count() == 0
    assert parts.balanced_partitioner(e, 4).parts == 4


def test_config(spark, data):
    from nearsort.sources import tables

    with pytest.raises(ValueError):
        SnConfig(w=1)
    e = tables.keyed(spark, data)
    for method in ("sequential", "stitch", "replica", "rank_bucket", "exploded"):
        assert candidates(e, SnConfig(method=method)).count() == 1755
    assert triples(candidates(e, SnConfig(w=150))) == triples(candidates(e, SnConfig(w=150, method="sequential")))


@pytest.mark.parametrize("w", [15, 101])
def test_engines_do_not_change_the_pairs(spark, data, w):
    from nearsort.sources import tables

    e = tables.keyed(spark, data)
    for method in ("stitch", "replica", "local"):
        for completeness in ("exact", "adjacent"):
            got = [triples(candidates(e, SnConfig(w=w, r=20, method=method, completeness=completeness, engine=engine))) for engine in ("frame", "bucket", "auto")]
            assert got[0] == got[1] == got[2]
    full, near = (len(triples(candidates(e, SnConfig(w=101, r=20, completeness=c)))) for c in ("exact", "adjacent"))
    assert near < full == measures.pair_count(e.count(), 101)


def test_all_pairs(spark, data):
    from nearsort.sources import tables

    e = tables.keyed(spark, data)
    got = [(r.left_id, r.right_id) for r in methods.cross_pairs(e, tile=30).collect()]
    assert len(got) == len(set(got)) == 19900 and all(a < b for a, b in got)


@pytest.fixture
def small_tiles(monkeypatch):
    from nearsort.operators import pairs

    monkeypatch.setattr(pairs, "TILE", 20)
    monkeypatch.setattr(pairs, "TASK_PAIRS", 500)


def largest_share(found):
    """Of the pairs, the share that the task with the most makes."""
    sizes = [r["count"] for r in found.groupBy(F.spark_partition_id()).count().collect()]
    return max(sizes) / sum(sizes)


HEAVY = [(k, "heavy" if k % 4 else None if k % 8 else f"k{k % 3}") for k in range(160)] + [(5, "heavy"), (5, "heavy"), (None, "heavy")]


def test_all_pairs_are_the_work_of_many_tasks(spark, small_tiles):
    found = methods.cross_pairs(spark.createDataFrame(HEAVY, "id long, k string"))
    ids = [i for i, _ in HEAVY if i is not None]
    assert sorted((r.left_id, r.right_id) for r in found.collect()) == sorted((a, b) for a in ids for b in ids if a < b)
    assert largest_share(found) < 0.3


def test_pairs_of_a_heavy_block_are_the_work_of_many_tasks(spark, small_tiles):
    found = methods.block_pairs(spark.createDataFrame(HEAVY, "id long, k string"))
    rows = [x for x in HEAVY if x[0] is not None]
    assert sorted((r.left_id, r.right_id) for r in found.collect()) == sorted((a, b) for a, k in rows for b, j in rows if a < b and k == j and k is not None)
    assert largest_share(found) < 0.3


def test_a_hash_join_of_a_heavy_block_is_the_work_of_many_tasks(spark, small_tiles):
    from nearsort.operators import relational as rel

    found = rel.same_key_join(spark.createDataFrame(HEAVY, "id long, k string"), "shuffle_hash")
    rows = [x for x in HEAVY if x[0] is not None]
    assert sorted((r.left_id, r.right_id) for r in found.collect()) == sorted((a, b) for a, k in rows for b, j in rows if a < b and k == j)
    assert largest_share(found) < 0.3
    assert "ShuffledHashJoin" in found._jdf.queryExecution().executedPlan().toString()


def test_pairs_of_a_heavy_band_are_the_work_of_many_tasks(spark, small_tiles):
    from nearsort.operators import relational as rel

    values = [(k, 7.0 if k % 3 else k / 10) for k in range(150)] + [(200, 1.0), (201, -1e-20), (202, None), (5, 7.0), (None, 7.0)]
    df = spark.createDataFrame(values, "id long, v double")
    found = rel.band_join(df, df, "v", 1.0)
    key = lambda x: tuple(-1 if y is None else y for y in x)
    want = sorted(((a, b) for a, x in values for b, y in values if x is not None and y is not None and abs(x - y) <= 1.0), key=key)
    assert sorted(((r.left_id, r.right_id) for r in found.collect()), key=key) == want
    assert largest_share(found) < 0.3


def bytes_a_pair(found, folder):
    found.write.parquet(str(folder))
    return sum(f.stat().st_size for f in folder.glob("*.parquet")) / found.sparkSession.read.parquet(str(folder)).count()


def moved(found):
    """Records that the plan's shuffles write."""
    spark = found.sparkSession
    adaptive = spark.conf.get("spark.sql.adaptive.enabled")
    try:
        spark.conf.set("spark.sql.adaptive.enabled", "false")
        found = found.agg(F.sum(F.hash("left_id", "right_id").cast("long")))
        found.collect()
        nodes, at = [found._jdf.queryExecution().executedPlan()], 0
        while at < len(nodes):
            below = nodes[at].children()
            nodes += [below.apply(i) for i in range(below.size())]
            at += 1
        return sum(n.metrics().apply("shuffleRecordsWritten").value() for n in nodes if n.nodeName() == "Exchange")
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", adaptive)


def test_all_pairs_move_no_copies_and_are_small(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(pairs, "TILE", 100)
    ids = spark.range(1500).select(F.xxhash64("id").alias("id"))
    found = methods.cross_pairs(ids)
    assert found.count() == 1500 * 1499 // 2
    assert moved(found) < 1500
    assert bytes_a_pair(found, tmp_path / "out") < 0.5


def test_bands_move_tiles_and_are_small(spark, tmp_path, monkeypatch):
    from nearsort.operators import relational as rel

    monkeypatch.setattr(pairs, "TILE", 600)
    df = spark.range(3000).select(F.xxhash64("id").alias("id"), (F.pmod(F.xxhash64("id"), F.lit(1500)) / 1000).alias("v"))
    found = rel.band_join(df, df, "v", 1.0)
    vs = [r.v for r in df.collect()]
    assert found.count() == sum(abs(a - b) <= 1.0 for a in vs for b in vs)
    assert moved(found) < 3000
    assert bytes_a_pair(found, tmp_path / "out") < 0.5


def test_a_band_makes_few_pairs_of_one_joined_row(spark, monkeypatch):
    """Rows of a heavy tile are not made all at once from one joined row: Spark holds in memory what one row makes."""
    from nearsort.operators import relational as rel

    df = spark.range(700).select("id", F.lit(7.0).alias("v"))
    monkeypatch.setattr(pairs, "LIST", 8)
    found = rel.band_join(df, df.select("id", "v"), "v", 1.0)
    assert found.count() == found.distinct().count() == 700 * 700
    found.collect()
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert plan.count("posexplode(right_ids") and "posexplode(left_ids" not in plan.split("SortMergeJoin")[0]


def test_balanced_cuts_far_and_near_agree(spark, data):
    from nearsort.sources import tables

    e = tables.keyed(spark, data)
    near, far = parts.balanced_partitioner(e, 7), parts.balanced_partitioner(e, 7, near=3)
    assert layout.tag(e, near).exceptAll(layout.tag(e, far)).isEmpty()


def test_composite_ranges_are_even(spark, data):
    from nearsort.sources import tables

    e = tables.keyed(spark, data).withColumn("k", F.lit("one heavy key"))
    sizes = layout.composite_range(e, 8).groupBy("p").agg(F.count("*").alias("rows"))
    assert measures.gini(sizes, 8).first()[0] < 0.2


def test_union_sorted(spark):
    a, b = (spark.createDataFrame(x, "id long") for x in ([(3,), (1,)], [(2,)]))
    assert [r.id for r in methods.union_sorted(a, b, order=("id",)).collect()] == [1, 2, 3]


def test_shuffle_report(spark, tmp_path):
    line = '{"Event":"SparkListenerTaskEnd","Task Info":{"Finish Time":%d},"Task Metrics":{"Disk Bytes Spilled":1,"Shuffle Write Metrics":{"Shuffle Bytes Written":%d}}}\n'
    (tmp_path / "log").write_text('{"Event":"Other"}\n' + line % (1000, 5) + line % (2000, 7))
    assert tuple(measures.shuffle_report(spark, str(tmp_path / "log")).first()) == (12, 2)
    assert tuple(measures.shuffle_report(spark, str(tmp_path / "log"), 1.5, 2.5).first()) == (7, 1)


def test_formulas():
    assert measures.pair_count(1000, 10) == measures.pair_count(1000, 10, closed=True) == 8955
    assert measures.pair_count(200, 1000) == 19900
    assert measures.missed_pairs([500, 500], 10) == measures.missed_pairs([500, 500], 10, closed=True) == 45
    assert measures.missed_pairs([5, 5], 100) == 25
    assert measures.speedup({1: 8.0, 4: 2.0}) == {1: 1.0, 4: 4.0}
    assert measures.replica_bound(3, 2, 3) == 6


@pytest.mark.parametrize("sizes, want", [((5, 5, 5, 5), 0), ((0, 0, 0, 4), 0.75), ((1, 2, 3, 4), 0.25), ((7,), 0)])
def test_gini(spark, sizes, want):
    df = spark.createDataFrame([(p, n) for p, n in enumerate(sizes) if n], "p int, rows long")
    assert measures.gini(df, len(sizes)).first()[0] == pytest.approx(want)


def test_partitioners_are_monotone(spark):
    ks = ["", "a", "ab", "zz", "É", "<h", "12", "  ", "🙂", "m", "n", "a{", "b`"]
    e = spark.createDataFrame(list(enumerate(ks)), "id long, k string")
    for p in (parts.even_partitioner(8), parts.even_partitioner(10), parts.balanced_partitioner(e, 4), parts.cut_partitioner(["b", "m"]), parts.halves()):
        parts.assert_monotone(layout.tag(e, p))


def test_link_and_multipass(spark):
    a = spark.createDataFrame([(1, "a"), (2, "c")], "id long, k string")
    b = spark.createDataFrame([(1, "b")], "id long, k string")
    assert {(r.left_id, r.right_id) for r in methods.link_pairs(a, b, 2).collect()} == {(1, 1), (2, 1)}
    e = spark.createDataFrame([(1, "a", "z"), (2, "b", "x"), (3, "c", "y")], "id long, one string, two string")
    got = {(r.left_id, r.right_id) for r in methods.multipass_pairs(e, [F.col("one"), F.col("two")], 2).collect()}
    assert got == {(1, 2), (2, 3), (1, 3)}


def test_plan_has_one_exchange(spark, data):
    from nearsort.sources import tables

    e = tables.publications(spark, data).select("id", "k")
    plan = methods.local_pairs(e, 5, parts.even_partitioner(8))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and "Cartesian" not in plan
    assert "ReadSchema: struct<doc_id:bigint,text:string>" in plan


def test_stitch_shares_its_wide_exchange(spark, data):
    """The rows are read and moved once; the second use is of the same exchange."""
    from nearsort.sources import tables

    e = tables.publications(spark, data).select("id", "k")
    adaptive = spark.conf.get("spark.sql.adaptive.enabled")
    try:
        spark.conf.set("spark.sql.adaptive.enabled", "false")
        plan = methods.stitch_pairs(e, 5, parts.even_partitioner(8))._jdf.queryExecution().executedPlan().toString()
        once = methods.replica_pairs(e, 5, parts.even_partitioner(8))._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", adaptive)
    assert plan.count("FileScan") == 1 and plan.count("shufflepartitionidpassthrough") - plan.count("ReusedExchange") == 1
    assert once.count("shufflepartitionidpassthrough") == 1 and "WindowGroupLimit" in once
