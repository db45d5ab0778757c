"""Headline queries and measured frames at $BENCH_SF_DIR on local[$BENCH_CPUS]; one JSON line.

Frames follow the published protocol: ten runs of each angle, their median, and the 75th percentile over angles as the frame time of a
cube. Times by nodes, frame size, executor and residence come from the same kind of runs.
"""

import json
import os
import sys
import tempfile
import time
from statistics import median, quantiles

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = ROOT + os.pathsep + os.environ.get("PYTHONPATH", "")
RUNS = 10


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    from cubecast import workloads
    from cubecast.operators import array_engine, composite, cube, render
    from cubecast.plans.kd import kd
    from cubecast.plans.spec import ANGLES, CUBES, SURVEY, ViewSpec
    from cubecast.sources import store

    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = (
        SparkSession.builder.master(f"local[{os.environ.get('BENCH_CPUS', '8')}]")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.shuffle.partitions", "8")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "8g")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    times: dict[str, float] = {}

    def drain(df):
        df.write.format("noop").mode("overwrite").save()

    def ms(f):
        t = time.time()
        f()
        return (time.time() - t) * 1000

    def timed(name, f):
        times[name] = round(ms(f) / 1000, 3)

    drain(workloads.QUERIES["m_bin_survey"](spark, sf))  # start-up is no query's time
    names = ["m_bin_survey", "m_cic", "m_exec_sql_30", "m_exec_arr_30", "m_int_t_array", "m_exec_obj_0", "m_color", "b_norect", "b_prev", "w1", "w2", "w3", "w6", "w7", "w11", "c_nm", "q_mom"]
    for n in names:
        timed(n, lambda n=n: drain(workloads.QUERIES[n](spark, sf)))

    def blocks(name, n):
        path = f"{tempfile.mkdtemp()}/blocks"
        store.write_blocks(array_engine.pack_bricks(cube.load(spark, sf, name), kd(CUBES[name].dims, n)), path)
        stored = store.read_bricks(spark, path)
        pinned = store.pin(stored.repartition(8, "brick", "block"))
        pinned.count()
        return stored, pinned

    def frame(rows, spec, shot):
        return composite.final(array_engine.cast(rows, spec, [shot]))

    def by_angle(rows, spec, side, angles, runs=RUNS):
        """Median of the runs of each angle, and their 75th percentile, in ms."""
        drain(frame(rows, spec, ViewSpec(7, side, side)))
        medians = {a: round(median(ms(lambda a=a: drain(frame(rows, spec, ViewSpec(a, side, side)))) for _ in range(runs)), 1) for a in angles}
        return {"median_ms": medians, "p75_ms": round(quantiles(medians.values(), n=4, method="inclusive")[2], 1) if len(medians) > 1 else next(iter(medians.values()))}

    runs: dict[str, object] = {}
    stored, pinned = blocks("survey", 16)
    runs["survey_16_128"] = by_angle(pinned, SURVEY, 128, ANGLES[:6])
    runs["size"] = {side: by_angle(pinned, SURVEY, side, (30,), 5)["p75_ms"] for side in (64, 128, 256, 512)}
    runs["residence"] = {k: by_angle(rows, SURVEY, 128, (30,), 5)["p75_ms"] for k, rows in (("pinned", pinned), ("storage", stored))}
    voxels = cube.survey(spark, sf).persist()
    voxels.count()
    drain(render.frame(voxels, SURVEY, ViewSpec(30)))
    sql = median(ms(lambda: drain(render.frame(voxels, SURVEY, ViewSpec(30)))) for _ in range(3))
    runs["executor"] = {"relational": round(sql, 1), "array": by_angle(pinned, SURVEY, 64, (30,), 3)["p75_ms"]}
    runs["nodes"] = {n: by_angle(blocks("survey_scaled", n)[1], CUBES["survey_scaled"], 128, (30,), 3)["p75_ms"] for n in (2, 4, 8, 16, 32, 64)}
    times["frame_latency_128"] = round(runs["survey_16_128"]["p75_ms"] / 1000, 3)
    for side in (128, 256):
        views = [ViewSpec(a, side, side, frame=i) for i, a in enumerate(ANGLES)]
        timed(f"batch_{len(views)}_frames_{side}", lambda views=views: drain(array_engine.cast(pinned, SURVEY, views).groupBy("frame", "u", "v").agg(F.max("val").alias("val"))))
    rate = {side: round(len(ANGLES) / times[f"batch_{len(ANGLES)}_frames_{side}"], 2) for side in (128, 256)}
    print(json.dumps({"metric": "total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "frames_per_second": rate, "runs": runs, "sf": sf}))


if __name__ == "__main__":
    main()
