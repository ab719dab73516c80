import glob
from concurrent.futures import ThreadPoolExecutor

import pytest
from pyspark.sql import functions as F

from bitplane.functions import udfs
from bitplane.functions.codecs import DecimalCodec, IntCodec
from bitplane.operators import encode
from bitplane.operators import select, skipping
from bitplane.operators.table import SlicedTable
from bitplane.plans import binding, predicates
from bitplane.sources import sliced as store
from bitplane.sources.datasource import SlicedDataSource
from bitplane.sources.tables import addressed, read_any, write_any
from bitplane.streaming import events

LONG = IntCodec(sql="bigint")


def table(spark, n=2000, files=4):
    df = spark.range(n).selectExpr(f"id % {files} as file_id", f"id div {files} as row_index", "id * 13 % 101 as x", "id as y").repartitionByRange(files, "file_id").sortWithinPartitions("file_id", "row_index")
    return SlicedTable.from_df(df, {"x": LONG, "y": LONG}), df


def test_write_read_append_compact(spark, tmp_path):
    t, df = table(spark)
    path = f"file://{tmp_path}/a"
    store.write_sliced(t, path)
    got = store.read_sliced(spark, path)
    assert got.manifest == t.manifest
    assert got.where("x > 50 AND y < 1000").count().first()[0] == df.where("x > 50 AND y < 1000").count()
    store.write_sliced(t, path, mode="append")
    assert store.read_sliced(spark, path).where("x > 50").count().first()[0] == 2 * df.where("x > 50").count()
    other = SlicedTable.from_df(df, {"x": DecimalCodec(), "y": LONG})
    with pytest.raises(ValueError, match="codec differs"):
        store.write_sliced(other, path, mode="append")
    with pytest.raises(ValueError, match="below the dataset's base"):
        SlicedTable.from_df(df.withColumn("x", F.col("x") - 5), {"x": LONG, "y": LONG}, like=t.manifest)
    store.compact(spark, path, f"file://{tmp_path}/b", 1)
    assert store.read_sliced(spark, f"file://{tmp_path}/b").all().count().first()[0] == 4000


def test_planes_are_pruned_and_extremes_pushed(spark, tmp_path):
    t, _ = table(spark)
    store.write_sliced(t, f"file://{tmp_path}/p")
    plan = store.read_sliced(spark, f"file://{tmp_path}/p").where("x > 50").count()._jdf.queryExecution().executedPlan().toString()
    assert "y__p0" not in plan and "x__p6" in plan and "GreaterThan(x__mx,50)" in plan


def test_data_source(spark, tmp_path):
    t, df = table(spark)
    store.write_sliced(t, str(tmp_path / "d"))
    spark.dataSource.register(SlicedDataSource)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    files = ",".join(glob.glob(str(tmp_path / "d/words/*.parquet")))
    load = lambda: spark.read.format("sliced").options(files=files, manifest=t.manifest.to_json()).load()
    assert load().where("x > 50 AND y < 1000 AND y % 2 = 0").orderBy("y").collect() == df.where("x > 50 AND y < 1000 AND y % 2 = 0").select("x", "y").orderBy("y").collect()
    assert load().count() == 2000


def test_sql_functions(spark):
    udfs.register(spark)
    planes = "array(13L, 108L, 201L)"
    row = spark.sql(f"SELECT bp_gt({planes}, 3L) & 239L AS gt, bp_ge({planes}, 3L) & 239L AS ge, bp_eq({planes}, 7L) AS eq, bp_between({planes}, 2L, 5L) & 239L AS bt, bp_in({planes}, array(0L, 7L)) & 239L AS isin").first()
    assert tuple(row) == (0xC9, 0xCD, 8, 1 | 4 | 32 | 128, 2 | 8)
    assert [r.pos for r in spark.sql("SELECT * FROM set_positions(201L)").collect()] == [0, 3, 6, 7]
    assert [(r.pos, r.value) for r in spark.sql(f"SELECT * FROM decode_word({planes}, 10L, 9L)").collect()] == [(0, 15), (3, 17)]
    got = spark.createDataFrame([(0, 5), (2, 3), (3, 7)], "pos long, v long").agg(udfs.slice_agg("pos", "v").alias("p")).first().p
    assert got == [13, 12, 9]


def test_formats(spark, tmp_path):
    df = spark.range(20).selectExpr("id", "cast(id as string) as s")
    for fmt in ("parquet", "orc", "csv", "json"):
        write_any(df, fmt, f"{tmp_path}/{fmt}")
        assert read_any(spark, fmt, f"{tmp_path}/{fmt}", "id bigint, s string").orderBy("id").collect() == df.collect()


@pytest.mark.parametrize("bias", ["block", "none"])
def test_appended_values_beyond_the_bounds(spark, tmp_path, bias):
    path = f"file://{tmp_path}/b"
    rows = lambda n, x: spark.range(n).selectExpr("id % 2 as file_id", "id div 2 as row_index", f"{x} as x").repartitionByRange(2, "file_id").sortWithinPartitions("file_id", "row_index")
    first, second, third = rows(500, "id % 100"), rows(500, "id % 121"), rows(100, "if(id % 4 = 0, null, id + 3000)")
    t = SlicedTable.from_df(first, {"x": LONG}, bias=bias)
    store.write_sliced(t, path)
    store.write_sliced(SlicedTable.from_df(second, {"x": LONG}, like=t.manifest), path, mode="append")
    every = first.union(second)
    for text in ("x <= 110", "x > 110", "x IS NULL", "x >= 0", "x = 120", "x BETWEEN 100 AND 130"):
        assert store.read_sliced(spark, path).where(text).count().first()[0] == every.where(text).count(), text
    store.write_sliced(SlicedTable.from_df(third, {"x": LONG}, like=t.manifest), path, mode="append")
    every = every.union(third)
    got = store.read_sliced(spark, path)
    assert (got.manifest["x"].lo, got.manifest["x"].hi, got.manifest["x"].has_nulls, got.manifest.rows) == (0, 3099, True, 1100)
    for text in ("x <= 110", "x > 110", "x IS NULL", "x IS NOT NULL", "x >= 0", "x > 3050", "x NOT IN (3, 3001)"):
        assert got.where(text).count().first()[0] == every.where(text).count(), text
    assert sorted(r.x for r in got.where("x > 90").fetch("x").collect()) == sorted(r.x for r in every.where("x > 90").collect())
    store.compact(spark, path, f"{path}-2", 1)
    assert store.read_sliced(spark, f"{path}-2").where("x > 110").count().first()[0] == every.where("x > 110").count()


def test_unfinished_parts_are_read_by_headers(spark, tmp_path):
    t, df = table(spark)
    path = f"file://{tmp_path}/u"
    with pytest.raises(RuntimeError):
        store.record(t.words, t.manifest, path, "part", lambda words: (words.write.parquet(f"{path}/words"), exec("raise RuntimeError"))[0])
    got = store.read_sliced(spark, path)
    assert not got.manifest.exact and got.manifest["x"].lo is None
    assert got.where("x > 50 AND y < 1000").count().first()[0] == df.where("x > 50 AND y < 1000").count()


def test_declared_manifest(spark, tmp_path):
    _, df = table(spark)
    m = encode.declare({"x": LONG, "y": LONG}, {"x": 7, "y": 12})
    store.write_sliced(SlicedTable.from_df(df, {"x": LONG, "y": LONG}, manifest=m), f"file://{tmp_path}/d")
    got = store.read_sliced(spark, f"file://{tmp_path}/d")
    assert got.manifest.exact and (got.manifest["y"].lo, got.manifest["y"].hi) == (0, 1999)
    assert got.where("x > 50").count().first()[0] == df.where("x > 50").count()
    with pytest.raises(Exception, match="needs 7 planes"):
        SlicedTable.from_df(df, {"x": LONG, "y": LONG}, manifest=encode.declare({"x": LONG, "y": LONG}, {"x": 6, "y": 12})).all().count().collect()


def test_late_fetch_does_not_shuffle_the_base(spark, tmp_path):
    df = spark.range(4000).selectExpr("id", "id % 100 as x", "cast(id as string) as s")
    df.coalesce(2).write.parquet(f"{tmp_path}/base")
    base = addressed(spark, f"{tmp_path}/base")
    got = SlicedTable.from_df(base, {"x": LONG}).where("x = 7").late("id", "s")
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "hashpartitioning" not in plan
    assert sorted(got.collect()) == sorted(df.where("x = 7").select("id", "s").collect())
    few = select.late(SlicedTable.from_df(base, {"x": LONG}).where("x = 7").masked, base, 1024, ["id", "s"], most=3)
    assert sorted(few.collect()) == sorted(got.collect())


def test_bloom_filters_in_headers(spark):
    df = spark.range(20000).selectExpr("0 as file_id", "id as row_index", "xxhash64(id) % 1000000 as x").coalesce(1)
    df = df.withColumn("x", F.when(F.col("row_index") % 50 == 0, None).otherwise(F.col("x")))
    t = SlicedTable.from_df(df.withColumn("file_id", F.col("file_id").cast("long")), {"x": LONG}, bias="block", bloom=("x",))
    held = [r.x for r in df.where("x is not null").limit(5).collect()]
    text = f"x IN ({', '.join(map(str, held))}, 5000001)"
    words = skipping.skipped(t.words, t.manifest, binding.bind(predicates.parse(text), t.manifest)).first()
    assert words.words == 313 and 1 <= words.kept < 60
    assert t.where(text).count().first()[0] == df.where(text).count()
    assert t.where(f"x = {held[0]} AND x > -2000000").count().first()[0] == df.where(f"x = {held[0]}").count()


def test_concurrent_predicates_on_one_cached_table(spark):
    t, df = table(spark)
    want = [df.where(f"x > {c}").count() for c in range(8)]
    with t, ThreadPoolExecutor(8) as pool:
        assert list(pool.map(lambda c: t.where(f"x > {c}").count().first()[0], range(8))) == want


def test_engine_by_calibration(spark):
    t, df = table(spark)
    assert t.where("x > 50", engine="auto").count().first()[0] == df.where("x > 50").count()
    took = t.calibrate("x > 50")
    assert set(took) == {"catalyst", "numpy"} and t.where("x > 50", engine="auto").count().first()[0] == df.where("x > 50").count()
    with pytest.raises(Exception, match="with constants only"):
        t.where("x > y", engine="numpy").count().collect()


def test_samples_repeat(spark):
    t, df = table(spark)
    one, two = (sorted(r.y for r in t.where("x > 10").sample(0.3, 5).fetch("y").collect()) for _ in "ab")
    n = df.where("x > 10").count()
    assert one == two and abs(len(one) - 0.3 * n) < 0.1 * n


def test_block_builder(spark, tmp_path):
    spark.range(2500).selectExpr("id % 2 as shard", "if(id = 77, null, id * 3 - 1000) as v").repartition(3).write.parquet(f"{tmp_path}/in")
    s = spark.readStream.schema("shard long, v long").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    out = events.finished(events.run_to_table(events.block_builder(s, "shard", "v", 256), "blocks"))
    assert {(r.shard, r.block): r.n for r in out.collect()} == {(k, b): 256 if b < 4 else 226 - k for k in (0, 1) for b in range(5)}
    got = events.unpacked(out).select("shard", "value").collect()
    assert sorted(map(tuple, got)) == sorted((i % 2, i * 3 - 1000) for i in range(2500) if i != 77)


def test_duplicates_within_watermark(spark, tmp_path):
    df = spark.sql("SELECT timestamp_ntz'2024-01-01 00:00:00' AS ts, id % 5 AS event_id FROM range(20)")
    df.coalesce(1).write.parquet(f"{tmp_path}/dup")
    s = spark.readStream.schema(df.schema).parquet(f"{tmp_path}/dup")
    assert events.run_to_table(events.deduplicated(s), "dedup").count() == 5
