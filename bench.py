"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Beside the queries' seconds it reports, for each code, bits per integer and millions of integers per second: of the
kernels (the sum of the tasks' own clocks) on synthetic lists, differential coding included and fused where a code can. `published` are the
"""

from __future__ import annotations

import json
import os
import statistics
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from laneforge.plans import pipeline  # noqa: E402
from laneforge.plans.queries import QUERIES  # noqa: E402
from laneforge.session import local_session, written  # noqa: E402
from laneforge.sources import synth  # noqa: E402

HEADLINE = [
    "flagship",
    "postings_documents",
    "delta1_documents",
    "block_width_by_or_128_documents",
    "patch_width_choice_documents",
    "size_vpack128_documents",
    "size_vpatch_documents",
    "roundtrip_vpack128_d1",
    "roundtrip_vpatch_d1_documents",
    "entropy_by_source_documents",
    "weighted_bits",
    "codec_choice_size",
    "intersect_pair",
    "intersect_query",
    "daily_encode",
    "stream_daily_counts",
]
#: Code, delta, and (bits, coding mis, decoding mis) as published for one long uniform list.
CODES = [
    ("vpack128", "s4", (8.0, 1900, 2600)),
    ("vpack128", "d1", (7.0, 1100, 1800)),
    ("vpatch", "s4", (7.6, 380, 2200)),
    ("vpatch", "d1", (6.4, 340, 1600)),
    ("linkpatch", "d1", (7.3, 360, 1300)),
    ("sizedpatch", "d1", (7.3, 280, 1300)),
    ("bucketpatch", "d1", (6.3, 330, 1200)),
    ("wordpatch", "d1", (6.3, 330, 1200)),
    ("pack32", "d1", (6.7, 810, 1200)),
    ("blockpatch10", "d1", (6.5, 110, 1000)),
    ("simple8b", "d1", (6.4, 370, 940)),
    ("bytegroup8", "s4", (9.0, 270, 1600)),
    ("bytegroup8", "d1", (9.0, 230, 1300)),
    ("splitvec", "d1", (7.2, 9.9, 790)),
    ("blockpatchopt", "d1", (6.2, 15, 740)),
    ("vbyte", "d1", (8.0, 930, 860)),
    ("generic_snappy", "d1", (None, None, None)),
]


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = local_session(cpus=int(os.environ.get("BENCH_CPUS", "8")), memory="12g")
    spark.sparkContext.setLogLevel("ERROR")
    took = {}
    for name in HEADLINE:
        runs = []
        for _ in range(2):  # the first run compiles
            start = time.time()
            QUERIES[name](spark, sf).write.format("noop").mode("overwrite").save()
            runs.append(time.time() - start)
        took[name] = round(min(runs), 3)
    codes = {}
    long_list = written(spark, pipeline.build_chunks(synth.gen_uniform(spark, 1, 1 << 20, 1 << 24)), "bench-long").repartition(int(os.environ.get("BENCH_CPUS", "8")))
    long_list = long_list.cache()
    long_list.count()
    for codec, delta, published in CODES:
        r = pipeline.measured(long_list, codec, delta, runs=3, fused=True).first()
        codes[f"{codec}/{delta}"] = {"bits": round(r["bits_per_int"], 2), "coding_mis": round(r["coding_mis"]), "decoding_mis": round(r["decoding_mis"]), "delta_share": round(r["delta_share"], 2), "published": published}
    print(json.dumps({"metric": "headline_queries_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "median": round(statistics.median(took.values()), 3), "codes": codes, "sf": sf}))


if __name__ == "__main__":
    main()
