"""python -m momenttree.workloads [directory] [experiment...]: runs the experiments and prints their rows as JSON lines."""

from __future__ import annotations

import json
import sys

from pyspark.sql import SparkSession

from momenttree.workloads import experiments as E

DIRECTORY = sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01"


def main() -> None:
    spark = SparkSession.builder.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    corpus = lambda name, **o: E.prepare(spark, DIRECTORY, name, **o)
    small = {"names": E.STUDIED, "sweeps": 2}
    known = {
        "runtime": lambda: E.total_runtime([corpus(n) for n in E.CORPORA]),
        "fraction": lambda: E.sweep(corpus("abstracts"), "fraction", [0.1, 0.25, 0.5, 1.0], **small),
        "height": lambda: E.sweep(corpus("abstracts"), "height", [1, 2, 3], width=3, **small),
        "width": lambda: E.sweep(corpus("abstracts"), "width", [2, 4, 6, 8, 10], **small),
        "vocabulary": lambda: E.vocab_sweep(spark, DIRECTORY),
        "variance": lambda: E.variance_study([corpus(n, top=200) for n in ("titles", "abstracts", "articles")]),
        "iterations": lambda: E.iteration_sweep(corpus("abstracts", top=400)),
        "intrusion": lambda: E.intrusion_study(spark, DIRECTORY, [corpus(n, top=400, stop=False) for n in ("titles", "articles")]),
        "recovery": lambda: E.recovery_study(spark),
    }
    for name in sys.argv[2:] or known:
        for row in known[name]():
            print(json.dumps({"experiment": name} | {k: round(x, 6) if isinstance(x, float) else x for k, x in row.items()}), flush=True)


main()
