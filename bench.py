"""Headline timings: prints one JSON line.

BENCH_SF_DIR: tables (default /root/testdata/sf0.1); BENCH_CPUS: local cores;
BENCH_COPIES: of each line item; BENCH_REPEATS: timed runs, of which the median
counts, after one that isn't timed.  Every sorter runs into the sink that drops
rows, on the same written workload, so that times hold sorting and not key
generation.

With BENCH_STORE, a file, it runs the sweeps named in BENCH_PARTS instead (sizes: all
sorters at three; records; cores: one to all) and writes their times there, from where the
measures of the registry read them (``digitsort/measured.json``).
"""

from __future__ import annotations

import json
import os
import statistics
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from digitsort.measures import throughput
from digitsort.operators import kmers, passes, sorts
from digitsort.plans.bins import Rules
from digitsort.session import release, table, written
from digitsort.sources import workloads as wl

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = int(os.environ.get("BENCH_CPUS", "8"))
REPEATS = int(os.environ.get("BENCH_REPEATS", "3"))
COPIES = int(os.environ.get("BENCH_COPIES", "8"))
STORE = os.environ.get("BENCH_STORE")

#: Sorters that move all rows once; and those that move them once for each digit, or hold partitions in Python.
FAST = {
    "adaptive_msd": lambda df: sorts.adaptive_msd(df, ["key"]),
    "msd_plain": lambda df: sorts.msd_plain(df, ["key"]),
    "sampled": lambda df: sorts.adaptive_msd(df, ["key"], sampled=True),
    "comparison": lambda df: sorts.comparison(df, ["key", "payload"]),
    "spark_default": lambda df: sorts.spark_default(df, ["key"]),
}
SLOW = {
    "lsd_plain": lambda df: sorts.lsd(df, "key", "pos"),
    "lsd_staged_64": lambda df: sorts.lsd(df, "key", "pos", 64),
    "lsd_staged_256": lambda df: sorts.lsd(df, "key", "pos", 256),
    "run_merge": lambda df: sorts.run_merge(df.select("key", "payload"), ["key", "payload"]),
    "inplace": lambda df: sorts.in_place(df.select("key", "payload"), "key", ["payload"]),
}


def session(cpus: int) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", str(2 * CPUS))
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def seconds(make, repeats: int = REPEATS) -> float:
    runs = []
    for k in range(repeats + (repeats > 1)):
        start = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        if k or repeats == 1:
            runs.append(time.perf_counter() - start)
    return round(statistics.median(runs), 3)


def interleaved(sorters: dict, df, repeats: int = REPEATS) -> dict[str, float]:
    """Medians of rounds in which each sorter runs once, so that a slower minute of the machine meets them all."""
    runs: dict[str, list[float]] = {k: [] for k in sorters}
    for k in range(repeats + 1):
        for name, f in sorters.items():
            t = seconds(lambda f=f: f(df), 1)
            if k:
                runs[name].append(t)
    return {k: round(statistics.median(v), 3) for k, v in runs.items()}


def loads(spark, copies: int, names: tuple[str, ...] = ("uniform", "zipf", "scatter")) -> dict:
    made = {"uniform": wl.uniform(spark, SF, copies), "zipf": wl.zipf(spark, SF, copies=copies), "scatter": wl.zipf(spark, SF, scatter=True, copies=copies)}
    return {k: written(v.select("key", "payload"), f"bench-{k}", "lz4") for k, v in made.items() if k in names}


def positioned(spark, source, sf: str, copies: int = 1):
    rows = passes.with_position(source(spark, sf, copies=copies), ["key", "payload", *wl.TIES])
    return written(rows.select("key", "payload", "pos"), "bench-positioned", "lz4")


def store(what: str, rows: list[dict]) -> None:
    """Replace one part of the stored times."""
    held = json.load(open(STORE)) if os.path.exists(STORE) else {}
    with open(STORE, "w") as f:
        json.dump(held | {what: rows}, f, indent=1)


def sweeps(sf: str, parts: list[str]) -> None:
    """Times of all sorters at three sizes, by the record's size, and by cores: each part is stored when it is done."""
    if "sizes" in parts:
        spark, rows = session(CPUS), []
        for copies in (1, 4, 16):
            for name, source in (("uniform", wl.uniform), ("zipf", wl.zipf)):
                df = positioned(spark, source, sf, copies)
                n = df.count()
                every = {k: (lambda df, f=f: f(df.select("key", "payload"))) for k, f in FAST.items()} | SLOW
                rows += [{"workload": f"{name}-{n}", "algorithm": k, "seconds": v} for k, v in interleaved(every, df, 1).items()]
                release(df)
        store("sizes", rows)
        spark.stop()
    if "records" in parts:
        spark, rows = session(CPUS), []
        for size in (8, 16, 24, 32):
            df = written(wl.record_size(spark, SF, size, COPIES).drop(*wl.TIES, "copy"), f"bench-rec{size}", "lz4")
            rows.append({"bytes": size, "seconds": seconds(lambda df=df: sorts.adaptive_msd(df, ["key"]))})
            release(df)
        store("records", rows)
        spark.stop()
    if "cores" in parts:
        rows = []
        for c in (c for c in (1, 2, 4, 8, 16) if c <= CPUS):
            spark = session(c)
            df = loads(spark, COPIES, ("uniform",))["uniform"]
            small = positioned(spark, wl.uniform, sf)
            times = interleaved({k: FAST[k] for k in ("adaptive_msd", "comparison", "spark_default")}, df, 1) | {k: seconds(lambda k=k: SLOW[k](small), 1) for k in ("lsd_staged_64", "lsd_staged_256")}
            rows += [{"algorithm": k, "workers": c, "seconds": v} for k, v in times.items()]
            store("cores", rows)
            spark.stop()


def main() -> None:
    if STORE:
        sweeps(os.environ.get("BENCH_SWEEP_DIR", os.path.join(os.path.dirname(SF), "sf0.01")), os.environ.get("BENCH_PARTS", "sizes,records,cores").split(","))
        return
    spark = session(CPUS)
    times: dict[str, float] = {}
    big = loads(spark, COPIES)
    rows = big["uniform"].count()
    for name, df in big.items():
        times |= {f"{k}_{name}": v for k, v in interleaved(FAST, df).items()}
    for name, source in (("uniform", wl.uniform), ("zipf", wl.zipf)):  # fewer rows: LSD moves them once for each digit
        df = positioned(spark, source, os.path.join(os.path.dirname(SF), "sf0.01"), 4)
        small = {"adaptive_msd": lambda df: sorts.adaptive_msd(df.select("key", "payload"), ["key"])}
        times |= {f"small_{k}_{name}": seconds(lambda f=f: f(df), 1) for k, f in (small | SLOW).items()}
    for size in (8, 16, 24, 32):
        df = written(wl.record_size(spark, SF, size, COPIES).drop(*wl.TIES, "copy"), f"bench-rec{size}", "lz4")
        times[f"record_{size}"] = seconds(lambda df=df: sorts.adaptive_msd(df, ["key"]))
        release(df)
    wide = written(wl.key16(spark, SF).drop(*wl.TIES), "bench-key16", "lz4")
    times["key16"] = seconds(lambda: sorts.adaptive_msd(wide, ["key_high", "key_low"]))
    grams = written(wl.kmers(spark, os.environ.get("BENCH_KMERS_DIR", os.path.join(os.path.dirname(SF), "sf0.01"))), "bench-kmers", "lz4")
    times |= {f"kmers_{k}": seconds(lambda f=f: f(grams, ["kmer"])) for k, f in (("adaptive_msd", sorts.adaptive_msd), ("comparison", sorts.comparison), ("spark_default", sorts.spark_default))}
    times["kmer_count"] = seconds(lambda: kmers.count(kmers.distribute(grams)), 1)
    times["orderkey_no_heavy_rule"] = seconds(lambda: sorts.adaptive_msd(table(spark, SF, "lineitem"), ["l_orderkey"], rules=Rules(heavy=None)))
    times["orderkey"] = seconds(lambda: sorts.adaptive_msd(table(spark, SF, "lineitem"), ["l_orderkey"]))
    headline = times["adaptive_msd_uniform"]
    rank = lambda w: sorted((k for k in FAST), key=lambda k: times[f"{k}_{w}"])
    more = {"rows": rows, **{k: round(v) for k, v in throughput(rows, 16, headline).items()}, "growth_32_over_8": round(times["record_32"] / times["record_8"], 3), **{f"rank_{w}": rank(w) for w in big}}
    print(json.dumps({"metric": "adaptive_msd_uniform", "value": headline, "unit": "sec", "queries": times, "sf": SF, **more}))


if __name__ == "__main__":
    main()
