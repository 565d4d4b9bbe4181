"""The published experiments on their stand-ins: prints one JSON line for each section.

Usage: python experiments.py [synthetic] [ratios] [growth] [blocks] [ablations]; BENCH_SF_DIR and
BENCH_CPUS choose the data and the cores. Results of a run are in EXPERIMENTS.md."""

from __future__ import annotations

import json
import os
import sys
import tempfile
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rowloom.operators import blocks as B
from rowloom.operators import order as O
from rowloom.operators import runs as R
from rowloom.operators.pilot import pilot_gain, sample_gain, shuffle_columns
from rowloom.operators.sizes import size
from rowloom.plans.flagship import comparison
from rowloom.plans.measures import SIX
from rowloom.plans.workloads import WORKS
from rowloom.sources.scratch import written
from rowloom.sources.synth import uniform_table, zipf_table

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
C4 = ["c1", "c2", "c3", "c4"]
CODES = [c + "__code" for c in C4]
TOURS = {
    "nearest_neighbor": ("nearest_neighbor", {}), "savings": ("savings", {}), "multiple_fragment": ("multiple_fragment", {}),
    "farthest_insertion": ("insertion", {"pick": "farthest"}), "nearest_insertion": ("insertion", {"pick": "nearest"}), "random_insertion": ("insertion", {"pick": "random"}),
}


def whole(df: DataFrame, codes: list[str], method: str, rows: int = 1 << 30, **opt) -> DataFrame:  # noqa: ANN003
    return written(B.run_blocks(df, [B.kernel(method, **opt)], codes, rows), "walked")


def synthetic(spark: SparkSession) -> dict:
    """Run reductions over the sorted order (of codes), and what improvements add to several tours."""
    out = {}
    for n in (8192, 131_072, 1_048_576):
        for name, make in (("zipf", zipf_table), ("uniform", uniform_table)):
            df = make(spark, n).select(*C4)
            orders = {o: O.order_by(df, o, C4, "given", keep_codes=True) for o in ("lexicographic", "interleave", "frequent_component")}
            base = R.total_runs(orders["lexicographic"], CODES)
            gain = lambda x: round(base / R.total_runs(x, CODES), 3)  # noqa: E731, B023
            got = {o: gain(orders[o]) for o in ("interleave", "frequent_component")}
            lists = whole(orders["lexicographic"], CODES, "multiple_lists", 131_072)
            got["multiple_lists"] = gain(lists)
            if n == 8192:
                tours = {label: whole(orders["lexicographic"], CODES, m, **opt) for label, (m, opt) in TOURS.items()}
                got |= {label: gain(t) for label, t in tours.items()}
                got |= {f"{o}+reinsertion": gain(whole(orders[o], CODES, "reinsertion")) for o in orders}
                for label, t in {**orders, "multiple_lists": lists, **tours}.items():
                    own = R.total_runs(t, CODES)
                    for m in ("peephole", "adjacent_swap"):
                        got[f"{label}+{m}, gain over itself"] = round(own / R.total_runs(whole(t, CODES, m), CODES), 4)
            out[f"{name} {n}"] = got
            print(json.dumps({f"{name} {n}": got}), file=sys.stderr, flush=True)
    return out


def ratios(spark: SparkSession) -> dict:
    """Sizes of the sorted order over the others, six stand-ins, six measures, two methods."""
    out = {}
    for w in SIX:
        rows = comparison(spark, SF_DIR, w, lz="lz4_raw").collect()
        out[w] = {m: {r["codec"]: round(r["ratio"], 3) for r in rows if r["method"] == m} for m in ("interleave", "multiple_lists_blocked")}
    return out


def growth(spark: SparkSession) -> dict:
    """Seconds of each order at four lengths of the star-schema table, stored as codes."""
    w = WORKS["ssb"]
    full = O.order_by(WORKS["ssb_larger"].frame(spark, SF_DIR), "lexicographic", w.cols, "given", keep_codes=True)
    codes = [c + "__code" for c in w.cols]
    stored = written(full.select(*codes).orderBy(F.xxhash64(*codes)), "codes")
    n, out = stored.count(), {}
    for share in (0.1, 0.2, 0.4, 1.0):
        part = written(stored.where(F.pmod(F.xxhash64(*codes, F.lit(1)), F.lit(1000)) < int(share * 1000)), "part")
        took = {"rows": part.count()}
        at = time.time()
        lex = O.order_by(part, "lexicographic", codes, "given")
        took["lexicographic"] = round(time.time() - at, 2)
        at = time.time()
        O.order_by(part, "interleave", codes, "given", normalize=False)
        took["interleave"] = round(time.time() - at, 2)
        at = time.time()
        whole(lex, codes, "multiple_lists", 131_072 // 8)
        took["lists after the sort"] = round(time.time() - at, 2)
        at = time.time()
        R.total_runs(lex, codes)
        took["run count"] = round(time.time() - at, 2)
        out[f"{share * n / 1e6:.2f} million"] = took
    return out


def blocks(spark: SparkSession) -> dict:
    """Run reduction and seconds of list walks by block size, on nine columns of the fact table and on readings."""
    out = {}
    for name in ("lineitem9", "weather"):
        w = WORKS[name]
        codes = [c + "__code" for c in w.cols]
        df = O.order_by(w.frame(spark, SF_DIR), "lexicographic", w.cols, "given", keep_codes=True)
        base = R.total_runs(df, codes)
        for rows in (128, 1024, 8192, 32_768, 131_072):
            at = time.time()
            got = whole(df, codes, "multiple_lists", rows)
            out[f"{name} {rows}"] = [round(base / R.total_runs(got, codes), 3), round(time.time() - at, 1)]
    return out


def ablations(spark: SparkSession) -> dict:
    """Columns shuffled apart, a row sample of 65,536, and the first 20 blocks of 131,072 rows."""
    w = WORKS["duplicates"]
    df = written(w.frame(spark, SF_DIR).withColumn("id", F.monotonically_increasing_id()), "with_ids")
    out = {}
    for label, frame in (("as it is", df.select(*w.cols)), ("columns shuffled apart", shuffle_columns(df, w.cols, "id").drop("pos"))):
        lex, inter = (O.order_by(frame, o, w.cols, "given", keep_codes=True) for o in ("lexicographic", "interleave"))
        codes = [c + "__code" for c in w.cols]
        walked = whole(lex, codes, "multiple_lists", 131_072)
        total = lambda x, codec: size(x, codec, codes).agg(F.sum("bits")).first()[0]  # noqa: E731, B023
        out[label] = {f"{m}, {codec}": round(total(lex, codec) / total(x, codec), 3) for m, x in (("interleave", inter), ("blocked lists", walked)) for codec in ("rle", "prefix")}
    out["interleave runs: whole table, 65,536 rows"] = [round(sample_gain(df.select(*w.cols), w.cols, n), 3) for n in (1 << 40, 65_536)]
    z = zipf_table(spark, 4_194_304).select(*C4)
    pilot = pilot_gain(z, C4, 20, 131_072).first()
    out["first 20 blocks of 32, Zipfian"] = [pilot["blocks"], round(pilot["gain"], 3)]
    return out


SECTIONS = {"synthetic": synthetic, "ratios": ratios, "growth": growth, "blocks": blocks, "ablations": ablations}


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", tempfile.mkdtemp(prefix="rowloom-experiments-"))
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    for name in sys.argv[1:] or SECTIONS:
        at = time.time()
        got = SECTIONS[name](spark)
        print(json.dumps({"section": name, "seconds": round(time.time() - at, 1), "results": got}), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()
