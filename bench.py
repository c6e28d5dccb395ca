"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

import atexit
import json
import os
import shutil
import sys
import tempfile
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    from pyspark.sql import SparkSession

    shared = tempfile.mkdtemp(prefix="bench-")  # one machine: its own folder is shared
    atexit.register(shutil.rmtree, shared, ignore_errors=True)
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", f"file://{shared}").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from privfreq.operators import model, reports, sketch, split
    from privfreq.params import SENSOR, ZIPF
    from privfreq.plans import kernels
    from privfreq.sources import tables
    from privfreq.sources.sinks import materialize

    words, parts = (lambda: tables.words(spark, SF_DIR)), (lambda: tables.parts(spark, SF_DIR))

    def split_state(c):
        table = materialize(sketch.exact(c).selectExpr("item", "cast(f as double) as g"), "scores")
        cut = split.find_boundary(table, ZIPF.theta)
        second = reports.assign_phase(c, ZIPF).where("phase = 2")
        return kernels.vector_state(split.mark_heavy(split.TableScorer(table).score(second), cut.p), ZIPF)

    def split_fitted(name, p, spec):
        c = tables.FIXTURES[name](spark, SF_DIR)
        domain = materialize(sketch.domain_of(c), "domain")
        return split.split_fit(c, domain, p, spec, t=50_000).estimate(domain)

    runs = {
        "exact_words": lambda: sketch.exact(words()),
        "onehot_state_words_1024x64": lambda: kernels.vector_state(words(), ZIPF),
        "split_state_words_1024x64": lambda: split_state(words()),
        "hadamard_words_1024x64": lambda: kernels.fast_hadamard(words(), sketch.domain_of(words()), ZIPF),
        "pooled_lh_words_128": lambda: sketch.local_hash_estimate(sketch.domain_of(words()), sketch.local_hash_state(reports.local_hash_reports(words(), ZIPF)), ZIPF),
        "onehot_parts_1024x64": lambda: kernels.gather_estimate(sketch.domain_of(parts()), kernels.vector_state(parts(), ZIPF), ZIPF),
        "countmin_words_1024x64": lambda: sketch.countmin_estimate(sketch.domain_of(words()), sketch.count_state(words(), ZIPF), ZIPF),
    }
    runs |= {
        "split_fitted_zipf_350x5": lambda: split_fitted("zipf", ZIPF, model.ZIPF_BOOSTED),
        "split_fitted_sensor_100x3": lambda: split_fitted("sensor_coarse", SENSOR, model.SENSOR_BOOSTED),
    }
    try:
        from privfreq.llm import registry

        runs |= {n: (lambda f=f: f(spark, SF_DIR)) for n, f in registry.QUERIES.items()}
    except ImportError:
        pass
    took = {}
    for name, f in runs.items():
        began = time.time()
        f().write.format("noop").mode("overwrite").save()
        took[name] = round(time.time() - began, 2)
    print(json.dumps({"metric": "total", "value": round(sum(took.values()), 2), "unit": "sec", "queries": took, "sf": SF_DIR}))


if __name__ == "__main__":
    main()
