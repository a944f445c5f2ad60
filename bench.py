"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; one JSON line.

The shuffled tables that sorts and builds start from are written first, whole and in B pieces,
so a time holds its own step alone: sort_* (to the noop sink), build_* (histograms, codes, sort
and payloads), count_*/eq12_* (from the index; eq12: twelve values, repeated inside one job).
"""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from sortbit.catalogue import pick_values
from sortbit.codes import numbered
from sortbit.index import IndexSpec, build_index
from sortbit.io import materialise
from sortbit.predicate import Eq
from sortbit.profile import load_histograms, save_histograms
from sortbit.roworder import GrayCode, NoOrder, PartitionSorted
from sortbit.workloads import PROJECTIONS

REPEATS = 30


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.driver.memory", "8g")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    took: dict[str, float] = {}

    def timed(name: str, f):
        began = time.perf_counter()
        out = f()
        took[name] = round(time.perf_counter() - began, 3)
        return out

    def run(df) -> None:
        df.write.format("noop").mode("overwrite").save()

    # code and workers are warm before anything counts
    warm = PROJECTIONS["p_gen"]
    small = warm.load(spark, sf_dir.replace("sf0.1", "sf0.01"))
    build_index(small, warm.names, warm.order("desc"), IndexSpec(block_rows=1 << 14)).fetch(Eq("l_linenumber", 3)).count()
    run(small.orderBy(*warm.names))

    for name in ("p_gen", "p_frequent"):
        p = PROJECTIONS[name]
        placed = materialise(numbered(p.order("shuffle").apply(p.load(spark, sf_dir)), "__pos"))
        n = placed.count()
        shuffled = materialise(placed.orderBy("__pos").drop("__pos"))
        pieces = {b: materialise(placed.repartitionById(b, F.floor(F.col("__pos") * b / n).cast("int")).sortWithinPartitions("__pos").drop("__pos")) for b in (5, 10, 500)}
        cols = tuple(reversed(p.names))

        timed(f"sort_{name}_full", lambda: run(p.order("desc").apply(shuffled)))
        timed(f"sort_{name}_asc", lambda: run(p.order("asc").apply(shuffled)))
        for b, df in pieces.items():
            timed(f"sort_{name}_blocks{b}", lambda: run(PartitionSorted(cols).apply(df)))
        timed(f"sort_{name}_gray", lambda: run(p.order("gray_desc").apply(shuffled)))
        timed(f"sort_{name}_gray_generic", lambda: run(GrayCode(cols, generic=True).apply(shuffled)))

        last = p.names[2]
        for k in (1, 2, 4):
            spec = IndexSpec(k=k, block_rows=1 << 17)
            built = {
                "full": timed(f"build_{name}_full_k{k}", lambda: build_index(shuffled, p.names, p.order("desc"), spec)),
                "none": timed(f"build_{name}_none_k{k}", lambda: build_index(shuffled, p.names, NoOrder(), spec)),
            }
            if k == 1:
                for b in (5, 10, 500):
                    built[f"blocks{b}"] = timed(f"build_{name}_blocks{b}_k1", lambda: build_index(pieces[b], p.names, PartitionSorted(cols), spec))
                at = f"/tmp/sortbit-bench-{os.getpid()}-{name}"
                save_histograms(shuffled, p.names, at)
                timed(f"build_{name}_full_k1_known_histograms", lambda: build_index(shuffled, p.names, p.order("desc"), spec, load_histograms(spark, at, p.names)))
            values = pick_values(built["full"].dicts[last], 12)
            for order, index in built.items():
                index.equality_counts(last, values).collect()
                timed(f"eq12_{name}_{order}_k{k}", lambda: index.equality_counts(last, values, REPEATS).collect())
            if k == 1:
                index = built["full"]
                for c in p.names:
                    value = pick_values(index.dicts[c], 3)[0]
                    index.count(Eq(c, value))
                    timed(f"count_{name}_{c}", lambda: index.count(Eq(c, value)))
                value = values[0]
                timed(f"fetch_{name}", lambda: index.fetch(Eq(last, value)).count())
                timed(f"scan_{name}", lambda: p.load(spark, sf_dir).where(F.col(last) == F.lit(value)).count())
    lines = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    many = materialise(lines.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(8)))).select("l_orderkey", "l_partkey", "l_suppkey", "copy"))  # about 5 million lines
    timed("sort_lines_x8", lambda: run(many.orderBy("l_partkey", "l_suppkey", "l_orderkey")))
    print(json.dumps({"metric": "headline_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": sf_dir.rstrip("/").rpartition("sf")[2]}))
    spark.stop()


if __name__ == "__main__":
    main()
