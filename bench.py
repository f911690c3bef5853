"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]: prints one JSON line. Each value is the seconds of one whole run."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))
SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").config("spark.sql.files.maxPartitionBytes", "4m").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from pairdict import codec, measures
    from pairdict.corpora import load, size_bytes
    from pairdict.sampling import SampleSpec
    from pairdict.training import train

    took, rates = {}, {}

    def timed(name, f):
        t = time.perf_counter()
        out = f()
        took[name] = round(time.perf_counter() - t, 3)
        return out

    for corpus, bits in (("headlines", 16), ("reviews_xl", 16), ("titles", 12)):
        c = load(spark, SF, corpus).repartition(int(CPUS) * 2).cache()
        raw = size_bytes(c)
        measures.timed(c)
        for variant in ("unbounded", "bounded16"):
            name = f"{corpus}_{variant}"
            d = timed(f"train_{name}", lambda: train(c, variant=variant, bits=bits, total_bytes=raw, sample=SampleSpec(max_bytes=8 << 20)))
            timed(f"encode_{name}", lambda: measures.timed(codec.encode(c, "value", d)))
            coded = codec.encode(c, "value", d).select("key", "payload").cache()
            n = coded.selectExpr("sum(octet_length(payload)) / 2").first()[0]
            timed(f"decode_{name}", lambda: measures.timed(codec.decode(coded, "payload", d)))
            rates[name] = {"ratio": round(measures.ratio(raw, n, d, bits), 3), "compress_mib_s": round(measures.throughput(raw, took[f"train_{name}"] + took[f"encode_{name}"]), 2), "decompress_mib_s": round(measures.throughput(raw, took[f"decode_{name}"]), 2)}
            coded.unpersist()
        c.unpersist()
    from pairdict.queries import queries

    q = queries()
    for name in ("point_access", "block_roundtrip_zstd", "bpe_roundtrip", "symtab8_roundtrip", "coverage_fixed", "o05_join_merge", "o12_interval_join"):
        timed(name, lambda name=name: measures.timed(q[name](spark, SF)))
    print(json.dumps({"metric": "headline queries", "value": round(sum(took.values()), 2), "unit": "sec", "queries": took, "rates": rates, "sf": SF.rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    main()
