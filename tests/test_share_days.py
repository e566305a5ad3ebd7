"""Closed days of a stream against the batch release with the same seed."""

import pytest
from pyspark.sql import functions as F

from pointveil import workloads
from pointveil.config import Cfg
from pointveil.functions.timeline import slot
from pointveil.operators import reach
from pointveil.plans import pipeline
from pointveil.sources import scenarios as S
from pointveil.streaming import share

D = "/root/testdata/sf0.001"


@pytest.mark.parametrize("files", [1, 4])
def test_a_stream_of_buckets_releases_the_batch_days(spark, tmp_path, files):
    cfg = Cfg(seed="7")
    poi, _, k = workloads.event_city(spark, D, cfg)
    # of a slot's visits the stream takes the least place
    key = F.concat_ws("|", F.col("user_id").cast("string"), F.date_format("ts", "yyyy-MM-dd"))
    traj = reach.valid_only(S.to_traj(S.visits(spark, D), key, slot(F.col("ts")), [F.col("poi_id")]), poi, cfg)
    want = {(r.traj_id, r.pos, r.poi_id, r.t) for r in pipeline.run("hier", traj, k, cfg).released.collect()}
    pts = S.visits(spark, D).select("user_id", F.col("ts").cast("timestamp").alias("ts"), "poi_id").toPandas().sort_values("ts", kind="stable")
    size = -(-len(pts) // files)
    parts = [pts.iloc[i : i + size] for i in range(0, len(pts), size)]
    schema = "user_id long, ts timestamp, poi_id string"
    for i, part in enumerate(parts):
        spark.createDataFrame(part, schema).coalesce(1).write.mode("append").parquet(str(tmp_path / f"in/{i}"))
    end = spark.createDataFrame([(0, "none")], "user_id long, poi_id string").select("user_id", F.lit("2030-01-01 00:00:00").cast("timestamp").alias("ts"), "poi_id")
    end.write.parquet(str(tmp_path / "in/z"))
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in/*"))
    out = share.share_days(share.stamped(stream), k, cfg, buckets=3)
    name = f"days{files}"
    out.writeStream.format("memory").queryName(name).outputMode("append").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start().awaitTermination()
    got = [tuple(r) for r in spark.table(name).collect()]
    assert len(got) == len(set(got)) and set(got) == want, (len(got), len(want), sorted(set(got) ^ want)[:12])
