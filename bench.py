"""Headline linkage queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

`queries` are the matchers for 3, 5 and 7 parties, whose sum is the value; `others` are the exact matcher it is
compared with and a register five times as large (keys of orders), for the trends over parties and size.
"""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ringlink import catalog
from ringlink.operators import baselines, registers
from ringlink.operators import linkage as L
from ringlink.spec import LinkageSpec


def main() -> None:
    d, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    conf = {"spark.sql.shuffle.partitions": cpus, "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false", "spark.driver.memory": "12g"}
    spark = SparkSession.builder.master(f"local[{cpus}]").config(map=conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")

    def timed(run) -> float:
        began = time.time()
        run().write.format("noop").mode("overwrite").save()
        return round(time.time() - began, 3)

    times, others = {}, {}
    for p in (3, 5, 7):
        spec = LinkageSpec(parties=p, block_keys=("given", "surname"))
        for mode in ("approx", "approx_filtered"):
            times[f"{mode}_p{p}"] = timed(lambda p=p, spec=spec, mode=mode: L.link(catalog.register(spark, d, p), spec, mode))
        others[f"exact_p{p}"] = timed(lambda p=p, spec=spec: baselines.exact_conjunction(catalog.register(spark, d, p), spec))
    keys = spark.read.parquet(f"{d}/orders.parquet").select(F.col("o_orderkey").alias("entity")).where("entity < 75000")
    spec = LinkageSpec(block_keys=("given", "surname", "postcode"))
    others["approx_filtered_p3_orders"] = timed(lambda: L.link(registers.make_register(registers.keyed_people(keys), 3), spec, "approx_filtered"))
    print(json.dumps({"metric": "linkage total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "others": others, "sf": d.rstrip("/").rpartition("sf")[2]}))


if __name__ == "__main__":
    main()
