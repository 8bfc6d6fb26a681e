"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; one JSON line."""

import json
import os
import time

from cellstream.operators import codelen, progressive, tree
from cellstream.operators.stream_codec import Codestream
from cellstream.plans import catalog
from cellstream.sources.shared import written
from cellstream.sources.workloads import LATTICES
from pyspark.sql import SparkSession

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main():
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "16g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    run = lambda df: df.write.format("noop").mode("overwrite").save()
    ev, li = LATTICES["events"], LATTICES["lineitem"]
    streams = {}

    def encode(name):
        stream = Codestream.encode(LATTICES[name].points(spark, SF), LATTICES[name].schedule(), path="sweep", tile_bits=6)
        stream.df = written(stream.df, "bench")
        streams[name] = stream

    queries = {
        "tree_events_explode": lambda: run(tree.count_tree(ev.points(spark, SF), ev.schedule())),
        "tree_events_sweep": lambda: run(tree.count_tree(ev.points(spark, SF), ev.schedule(), "sweep")),
        "tree_lineitem_sweep": lambda: run(tree.count_tree(li.points(spark, SF), li.schedule(), "sweep")),
        "summary_lineitem": lambda: run(codelen.summary(tree.count_tree(li.points(spark, SF), li.schedule(), "sweep"), li.schedule().q)),
        "encode_events": lambda: encode("events"),
        "decode_events": lambda: run(streams["events"].cells()),
        "decode_events_12_waves": lambda: run(streams["events"].cells(12)),
        "rate_curve_events": lambda: run(catalog.CATALOG["rate_curve_events"][0](spark, SF)),
        "roi_cost": lambda: run(catalog.CATALOG["roi_cost"][0](spark, SF)),
        "exp_progressive": lambda: run(catalog.CATALOG["exp_progressive"][0](spark, SF)),
        "distortion": lambda: run(progressive.distortion(ev.points(spark, SF), ev.schedule(), [6, 12, 24])),
    }
    # Warm-up: each path once on the smallest tables, so that the first query does not pay for the start.
    small = os.path.join(os.path.dirname(SF.rstrip("/")), "sf0.001")
    if os.path.isdir(small):
        for path in ("explode", "sweep"):
            run(tree.count_tree(ev.points(spark, small), ev.schedule(), path))
        run(Codestream.encode(ev.points(spark, small), ev.schedule(), path="sweep", tile_bits=6).cells())
    took = {}
    for name, q in queries.items():
        t = time.time()
        q()
        took[name] = round(time.time() - t, 3)
    # Linear time: the sweep of the largest lattice at each size that there is, by points.
    scaling = {}
    for other in ("sf0.001", "sf0.01", os.path.basename(SF.rstrip("/"))):
        place = os.path.join(os.path.dirname(SF.rstrip("/")), other)
        if os.path.isdir(place):
            t = time.time()
            run(codelen.summary(tree.count_tree(li.points(spark, place), li.schedule(), "sweep"), li.schedule().q))
            scaling[str(li.points(spark, place).count())] = round(time.time() - t, 3)
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(SF.rstrip("/")), "seconds_by_points": scaling, "decode_to_encode": round(took["decode_events"] / took["encode_events"], 3)}))


if __name__ == "__main__":
    main()
