from pyspark.sql import functions as F

from vistapoint import workloads as W
from vistapoint.operators import cube, matrix
from vistapoint.sources import carriers, store
from vistapoint.streaming import ingest

DIR = "/root/testdata/sf0.001"


def split(spark, path):
    spark.read.parquet(f"{DIR}/events.parquet").repartition(4, "event_id").write.parquet(path)
    return path


def test_ingested_store_equals_the_batch(spark, tmp_path):
    source = split(spark, f"{tmp_path}/in")
    ingest.ingest(ingest.event_stream(spark, source), f"{tmp_path}/store", f"{tmp_path}/ck").awaitTermination()
    got = store.read(spark, f"{tmp_path}/store").select("fov_id", "min_lat", "max_lon", "tile_id")
    want = store.laid_out(carriers.from_events(spark, DIR)).select("fov_id", "min_lat", "max_lon", "tile_id")
    assert got.exceptAll(want).count() == want.exceptAll(got).count() == 0


def test_cube_from_a_stream_equals_the_matrix(spark, tmp_path):
    source = split(spark, f"{tmp_path}/in")
    fovs = W.fov.with_mbr(carriers.events_to_fovs(ingest.event_stream(spark, source)))
    ingest.maintain_cube(fovs, W.T1, f"{tmp_path}/cube", f"{tmp_path}/ck").awaitTermination()
    total = cube.over(spark.read.parquet(f"{tmp_path}/cube"))
    exact = matrix.optimized(W.events(spark, DIR), W.T1)
    assert total.exceptAll(exact).count() == exact.exceptAll(total).count() == 0


def test_streamed_windows_and_duplicates(spark, tmp_path):
    source = split(spark, f"{tmp_path}/in")
    split(spark, f"{tmp_path}/again")
    spark.read.parquet(f"{tmp_path}/again").write.mode("append").parquet(source)
    fovs = ingest.deduplicated(carriers.events_to_fovs(ingest.event_stream(spark, source, 100)), "60 days")
    counted = fovs.groupBy(F.window("t", "1 day").alias("w")).agg(F.count("*").alias("n"))
    counted.writeStream.format("memory").queryName("daily").outputMode("complete").trigger(availableNow=True).option("checkpointLocation", f"{tmp_path}/ck2").start().awaitTermination()
    got = {r.n for r in spark.sql("select sum(n) as n from daily").collect()}
    assert got == {1000}


def test_store_prunes_days_and_pushes_the_box(spark, tmp_path):
    store.write(carriers.from_events(spark, DIR), f"{tmp_path}/s", 2)
    found = W.retrieval.fovs_in_range(store.read(spark, f"{tmp_path}/s"), W.T1.area, W.JANUARY)
    spark.conf.set("spark.sql.maxMetadataStringLength", 5000)
    text = found._jdf.queryExecution().executedPlan().toString()
    spark.conf.unset("spark.sql.maxMetadataStringLength")
    assert "day" in text.split("PartitionFilters: [")[1].split("]")[0] and "LessThanOrEqual(min_lat" in text.split("PushedFilters: [")[1]


def test_refined_range_query_keeps_every_true_overlap(spark):
    fovs = W.events(spark, DIR, "mix30")
    loose, tight = W.retrieval.fovs_in_range(fovs, W.T0.area), W.retrieval.fovs_in_range(fovs, W.T0.area, refine=True)
    seen = matrix.exploded(loose, W.T0, ("fov_id",)).select("fov_id").distinct()
    assert seen.join(tight, "fov_id", "left_anti").count() == 0 and tight.count() <= loose.count()
