"""Matchers on literals, and the short circuit against the full mean."""

import random
import time

import pytest
from pyspark.sql import functions as F

from nearsort.functions import keys, matching as m
from nearsort.operators import components, relational as rel
from nearsort.plans.resolve import SnConfig, resolve
from nearsort.sources import tables


def one(spark, *cols, **values):
    df = spark.createDataFrame([tuple(values.values())], ", ".join(f"{k} string" for k in values))
    return df.select(*cols).first()


def test_literals(spark):
    a, b = F.col("a"), F.col("b")
    r = one(spark, m.edit_similarity(a, b), m.bounded_edit(a, b, 0.5), m.bounded_edit(a, b, 0.9), a="kitten", b="sitting")
    assert [round(x, 6) for x in r] == [round(4 / 7, 6), round(4 / 7, 6), 0.0]
    assert set(one(spark, m.trigrams(a), a="abcdab", b="")[0]) == {"abc", "bcd", "cda", "dab"}
    assert list(one(spark, m.trigram_similarity(a, b), m.trigram_similarity(a, b, "jaccard"), a="abcd", b="bcde")) == [0.5, 1 / 3]
    assert list(one(spark, m.trigram_similarity(a, b), m.edit_similarity(a, b), a="", b="")) == [1.0, 1.0]
    assert list(one(spark, m.trigram_similarity(a, b), m.edit_similarity(a, b), a=None, b="xyz")) == [0.0, 0.0]
    assert one(spark, m.combine([(F.lit(1.0), 3.0), (F.lit(0.0), 1.0)]), a="", b="")[0] == 0.75
    assert one(spark, m.ascii_fold(a), a="é🙂x", b="")[0] == "??x"


def test_keys(spark):
    r = one(spark, keys.prefix_key("a"), keys.suffix_key("a"), keys.concat_prefix_key([("a", 1), ("b", 2)]), keys.host_key("b"), a="Éclair", b="http://X.org/y")
    assert list(r) == ["éc", "air", "éht", "x.org"]
    assert one(spark, keys.prefix_key("a"), keys.host_key("b"), a=None, b="nothing") == ("", "")


def test_short_circuit_changes_nothing(spark, data):
    e = tables.publications(spark, data, features=True)
    early, late = ("title_ascii",), ("abstract",)
    fast = {tuple(r) for r in resolve(e, SnConfig(), m.TitleAbstract(), early, late).collect()}
    slow = {tuple(r) for r in resolve(e, SnConfig(method="rank_bucket"), m.TitleAbstract(skip=False), early + late).collect()}
    assert fast == slow and fast


def test_array_forms_agree_with_the_functions(spark):
    rnd = random.Random(4)
    text = lambda: "".join(rnd.choices("abé🙂 ", k=rnd.choice([0, 1, 2, 3, 20, 64, 65, 90])))
    rows = [(None, "x"), ("same", "same"), ("", ""), ("ab", "ab")] + [(x := text(), rnd.choice([text(), x[1:] + "b"])) for _ in range(200)]
    a, b = F.col("a"), F.col("b")
    df = spark.createDataFrame(rows, "a string, b string")
    got = df.select(a, b, m.bounded_edit(a, b, 0.5).alias("e"), m.text_edit_similarity(a, b, 0.5).alias("f"), m.trigram_similarity(a, b).alias("g"), m.text_gram_similarity(a, b).alias("h")).collect()
    for r in got:
        assert r.e == pytest.approx(r.f) and r.g == pytest.approx(r.h), (r.a, r.b)


def test_classifier_is_judged_on_pairs_it_has_not_seen(spark, data):
    from nearsort.queries import QUERIES

    rows = QUERIES["er_learned"](spark, data.replace("sf0.001", "sf0.01")).collect()  # the smallest table has twelve pairs of copies
    hit = sum(r.label == 1 and r.prediction == 1 for r in rows)
    assert hit and hit >= 0.9 * sum(r.label for r in rows)  # copies are found, and besides them only near copies
    assert sum(r.prediction for r in rows) <= 0.05 * len(rows)


def test_clusters(spark):
    pairs = spark.createDataFrame([(1, 2), (2, 3), (9, 8), (3, 1), (20, 21), (21, 22), (22, 23), (23, 24)], "left_id long, right_id long")
    assert {(r.id, r.cluster) for r in components.clusters(pairs).collect()} == {(1, 1), (2, 1), (3, 1), (8, 8), (9, 8), (20, 20), (21, 20), (22, 20), (23, 20), (24, 20)}
    assert components.clusters(pairs.limit(0)).count() == 0


def test_pair_diff(spark):
    a = spark.createDataFrame([(1, 2), (2, 3)], "left_id long, right_id long")
    b = spark.createDataFrame([(2, 3), (4, 5)], "left_id long, right_id long")
    assert {tuple(r) for r in rel.pair_diff(a, b).collect()} == {(1, 2, "left"), (4, 5, "right")}


def test_stream_replay(spark, data, tmp_path):
    from nearsort.operators.partitioners import balanced_partitioner
    from nearsort.streaming.events import IncrementalPairs

    e = tables.keyed(spark, data).select("id", "k")
    inc = IncrementalPairs(spark, balanced_partitioner(e, 4), 5, str(tmp_path))
    inc(e.where("id % 2 = 0"), 0)
    inc(e.where("id % 2 = 1"), 1)
    first = sorted(map(tuple, inc.results().collect()))
    inc(e.where("id % 2 = 1"), 1)
    assert sorted(map(tuple, inc.results().collect())) == first


def test_late_rows_are_counted(spark, tmp_path):
    from nearsort.streaming import events as streams

    folder = tmp_path / "in"
    for at in ("03:50", "03:51", "02:10"):  # the third file lies behind the watermark of the first, which holds from then on
        spark.createDataFrame([(f"2024-01-01 {at}:00", "x")], "ts string, event_type string").coalesce(1).write.mode("append").parquet(str(folder))
        time.sleep(1.1)
    stream = spark.readStream.schema("ts string, event_type string").option("maxFilesPerTrigger", 1).parquet(str(folder)).withColumn("ts", F.col("ts").cast("timestamp"))
    query = streams.tumbling_counts(stream).writeStream.format("noop").outputMode("append").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
    query.awaitTermination()
    assert streams.late_rows(query) == 1


def test_sinks_and_sources(spark, tmp_path):
    from nearsort.operators import layout, partitioners as parts
    from nearsort.sources import sinks

    found = spark.createDataFrame([(1, 2, "a"), (2, 3, "b")], "left_id long, right_id long, k string")
    sinks.write_pairs(found, str(tmp_path / "pairs"), by="k")
    assert sorted(p.name for p in (tmp_path / "pairs").glob("k=*")) == ["k=a", "k=b"] and spark.read.parquet(str(tmp_path / "pairs")).count() == 2
    (tmp_path / "rows.csv").write_text("7,Ab\n8,cd\n")
    e = tables.load_entities(spark, str(tmp_path / "rows.csv"), "csv", "n long, title string", "n", keys.prefix_key("title"))
    assert {tuple(r) for r in e.select("id", "k", "title").collect()} == {(7, "ab", "Ab"), (8, "cd", "cd")}
    spark.sql(f"CREATE DATABASE layouts LOCATION '{tmp_path}/db'")
    sinks.save_layout(layout.ordered(e, parts.cut_partitioner(["b"])), "layouts.some", 2)
    assert {(r.id, r.p) for r in spark.table("layouts.some").collect()} == {(7, 0), (8, 1)}
    spark.sql("DROP DATABASE layouts CASCADE")


def test_samples_and_sketches(spark, data):
    e = tables.keyed(spark, data)
    assert abs(rel.approx_distinct_keys(e).first()[0] - rel.distinct_keys(e).first()[0]) <= 0.15 * rel.distinct_keys(e).first()[0]
    cuts = rel.cut_points(e, "id", 4).first()[0]
    assert len(cuts) == 3 and cuts == sorted(cuts)
    assert 0 < rel.sample_keys(e, 0.5).count() < e.count()
    assert sum(x.count() for x in rel.random_split(e, [0.3, 0.7])) == e.count()
