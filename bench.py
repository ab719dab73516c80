"""Scans of encoded and of plain tables at 1, 10 and 50 million rows: one JSON line.

The tables of $BENCH_SF_DIR are written ``times`` over as Parquet, encoded once under a declared manifest, and
scanned from the files by queries that are rebuilt for every run; local[$BENCH_CPUS].  ``queries`` holds the medians of
the runs after the warm-up (seconds), ``detail`` the figures derived from them.  $BENCH_SIZES (millions of rows) changes the sizes.
A measure stops repeating after CAP seconds.  A size is left out (``detail.skipped``) once $BENCH_BUDGET seconds are two fifths gone, and
the other kinds of predicates once they are three quarters gone.
"""

from __future__ import annotations

import json
import os
import shutil
import statistics
import sys
import tempfile
import time

#: Patterns: table, encoded predicate, plain predicate.
PATTERNS = {
    "q1_quantity": ("lineitem", "quantity > 25", "quantity > 25"),
    "q2_offset": ("orders", "total BETWEEN 1000 AND 36000", "total BETWEEN 1000 AND 36000"),
    "q3_dates": ("lineitem", "ship BETWEEN DATE '1995-01-01' AND DATE '1996-05-15'", "ship BETWEEN DATE '1995-01-01' AND DATE '1996-05-15'"),
    "q4_skewed": ("orders", "total > 493000", "total > 493000"),
    "q5_compound": ("lineitem", "quantity > 12 AND price BETWEEN 5000 AND 80000", "quantity > 12 AND price BETWEEN 5000 AND 80000"),
}
#: The throughput columns, and other kinds of predicates and types, at the middle size.
KINDS = {
    "d1_quantity": ("lineitem", "quantity > 25"), "d2_price": ("lineitem", "price > 52923.5"), "d3_key": ("orders", "key > {half}"),
    "kind_eq": ("lineitem", "quantity = 25"), "kind_between": ("lineitem", "quantity BETWEEN 10 AND 19"), "kind_in4": ("lineitem", "quantity IN (3, 17, 30, 44)"),
    "kind_in16": ("lineitem", "quantity IN (1, 4, 7, 10, 13, 16, 19, 22, 25, 28, 31, 34, 37, 40, 43, 46)"),
    "date_gt": ("lineitem", "ship > DATE '1998-01-01'"), "date_eq": ("lineitem", "ship = DATE '1998-01-01'"),
    "string_eq": ("orders", "priority = '1-URGENT'"), "string_in": ("orders", "priority IN ('1-URGENT', '5-LOW')"),
}
CUTS = {"0.1%": 104875.15, "1%": 103940.14, "10%": 94709.31, "50%": 53028.16, "90%": 11352.49}
PLAIN = {
    "lineitem": ["cast(l_quantity as int) quantity", "l_extendedprice price", "cast(l_shipdate as date) ship"],
    "orders": ["o_orderkey + copy * {rows} key", "o_totalprice total", "o_orderpriority priority"],
}


CAP = 4.0


def main() -> None:
    begun, budget = time.perf_counter(), float(os.environ.get("BENCH_BUDGET", "480"))
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    sizes = [float(x) for x in os.environ.get("BENCH_SIZES", "1,10,50").split(",")]
    from pyspark.sql import functions as F

    from bitplane.functions import metrics
    from bitplane.functions.codecs import DateCodec, DecimalCodec, IntCodec
    from bitplane.operators import baselines, dictionary, encode
    from bitplane.operators.table import SlicedTable
    from bitplane.session import get_session
    from bitplane.sources import sliced as store
    from bitplane.sources.tables import addressed, load

    spark = get_session("bench", f"local[{cpus}]", spark__sql__shuffle__partitions=cpus, spark__ui__enabled="false", spark__ui__showConsoleProgress="false", spark__driver__memory="8g")
    spark.sparkContext.setLogLevel("ERROR")
    root = tempfile.mkdtemp(prefix="bitplane-bench-")
    queries: dict[str, float] = {}
    detail: dict[str, object] = {}
    beans = spark._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans()

    def gc_seconds() -> float:
        return sum(b.getCollectionTime() for b in beans) / 1000

    def timed(name: str, run, runs: int = 10, warm: int = 5) -> float:
        took = []
        first = time.perf_counter()
        for _ in range(warm + runs):
            start = time.perf_counter()
            run()
            took.append(time.perf_counter() - start)
            if len(took) > 2 and time.perf_counter() - first > CAP:
                break
        took = took[min(warm, len(took) // 3) :]
        queries[name] = statistics.median(took)
        if len(took) > 2:
            mean, half = metrics.mean_ci(took)
            detail[f"{name}_mean_ci999"] = [round(mean, 4), round(half, 4), len(took)]
        print(f"{time.perf_counter() - begun:7.1f} {name} {queries[name]:.4f}", file=sys.stderr, flush=True)
        return queries[name]

    def folder_bytes(path: str) -> int:
        return sum(os.path.getsize(os.path.join(at, f)) for at, _, files in os.walk(path) for f in files if f.endswith(".parquet"))

    known = dictionary.build(load(spark, sf_dir, "orders"), "o_orderpriority")
    codecs = {
        "lineitem": {"quantity": IntCodec(), "price": DecimalCodec(scale=2), "ship": DateCodec()},
        "orders": {"key": IntCodec(sql="bigint"), "total": DecimalCodec(scale=2), "priority": known},
    }
    planes = {"quantity": 6, "price": 24, "ship": 14, "key": 10, "total": 26, "priority": 3}
    biases = {c: "none" for c in planes} | {"key": "block"}  # keys ascend, so a block's are close together
    middle, done, kept = sorted(sizes)[len(sizes) // 2], [], None
    for size in sizes:
        if done and time.perf_counter() - begun > 0.4 * budget:
            detail.setdefault("skipped", []).append(f"{size:g}m")
            continue
        done.append(size)
        tag, plain, sliced, wrote = f"{size:g}m", {}, {}, {}
        for name, cols in PLAIN.items():
            base = load(spark, sf_dir, name)
            rows = base.count()
            times = max(1, round(size * 1e6 / rows))
            path = f"{root}/{name}-{tag}"
            copies = spark.range(0, times, 1, min(times, int(cpus))).withColumnRenamed("id", "copy").crossJoin(F.broadcast(base))
            copies.selectExpr(*[c.format(rows=rows) for c in cols]).write.parquet(path)
            plain[name] = spark.read.parquet(path)
            n = rows * times
            start = time.perf_counter()
            m = encode.declare(codecs[name], {c: planes[c] for c in codecs[name]}, biases)
            store.write_sliced(SlicedTable.from_df(addressed(spark, path), codecs[name], manifest=m), f"{path}-sliced")
            wrote[name] = time.perf_counter() - start
            queries[f"encode_{name}_{tag}"] = wrote[name]
            print(f"{time.perf_counter() - begun:7.1f} encode {name} {tag} {wrote[name]:.2f}", file=sys.stderr, flush=True)
            detail[f"encode_{name}_{tag}_ms_per_m_rows"] = round(metrics.encode_rate(wrote[name] * 1000, n), 1)
            sliced[name] = store.read_sliced(spark, f"{path}-sliced")
            detail[f"bytes_per_row_{name}_{tag}"] = {"sliced": round(folder_bytes(f"{path}-sliced") / n, 3), "plain": round(folder_bytes(path) / n, 3)}
        for name, (tab, text, condition) in PATTERNS.items():
            n = plain[tab].count()
            gc = gc_seconds()
            fast = timed(f"{name}_{tag}", lambda t=tab, x=text: sliced[t].where(x).count().collect())
            detail[f"{name}_{tag}_gc"] = [round(gc_seconds() - gc, 3)]
            gc = gc_seconds()
            slow = timed(f"{name}_{tag}_scalar", lambda t=tab, x=condition: baselines.scalar(plain[t], x).collect())
            detail[f"{name}_{tag}_gc"].append(round(gc_seconds() - gc, 3))
            assert sliced[tab].where(text).count().first()[0] == baselines.scalar(plain[tab], condition).first()[0], name
            detail[f"{name}_{tag}_speedup"] = round(slow / fast, 2)
            detail[f"{name}_{tag}_m_rows_per_s"] = [round(n / fast / 1e6), round(n / slow / 1e6)]
            detail[f"{name}_{tag}_break_even_scans"] = round(metrics.break_even(wrote[tab], slow, fast), 1) if slow > fast else None
        if size == middle:
            kept = tag, plain, sliced
    # The sizes come first, so that the kinds at the middle size do not use up the time of the largest.
    if time.perf_counter() - begun > 0.75 * budget:
        detail.setdefault("skipped", []).append("kinds")
    elif kept:
        tag, plain, sliced = kept
        for name, (tab, text) in KINDS.items():
            text = text.format(half=plain[tab].count() // 2)
            fast = timed(f"{name}_{tag}", lambda t=tab, x=text: sliced[t].where(x).count().collect(), 5, 2)
            slow = timed(f"{name}_{tag}_scalar", lambda t=tab, x=text: baselines.scalar(plain[t], x).collect(), 5, 2)
            detail[f"{name}_{tag}_speedup"], detail[f"{name}_passes"] = round(slow / fast, 2), sliced[tab].explain(text)["passes"]
        rates = {"sliced": [], "scalar": []}
        for name, cut in CUTS.items():
            text = f"price > {cut}"
            rates["sliced"].append(1 / timed(f"selectivity_{name}_{tag}", lambda x=text: sliced["lineitem"].where(x, mode="oblivious").count().collect(), 5, 2))
            rates["scalar"].append(1 / timed(f"selectivity_{name}_{tag}_scalar", lambda x=text: baselines.scalar(plain["lineitem"], x).collect(), 5, 2))
        detail["selectivity_spread"] = {k: round(metrics.spread(v), 3) for k, v in rates.items()}
        q1 = plain["lineitem"]
        timed(f"q1_arrow_{tag}", lambda: baselines.arrow(q1, "quantity", "gt", 25).collect(), 2, 1)
        timed(f"q1_materialised_{tag}", lambda: baselines.parquet_materialised(q1, "quantity > 25").collect(), 2, 1)
        timed(f"q1_numpy_{tag}", lambda: sliced["lineitem"].where("quantity > 25", engine="numpy").count().collect(), 2, 1)
        timed(f"q1_boxed_{tag}", lambda: baselines.boxed(q1.limit(1_000_000), "quantity", lambda x: x > 25).collect(), 1, 0)
        # Cached tables: planes against Spark's columnar cache.
        q1, words = q1.select("quantity").persist(), sliced["lineitem"].words.select("live", *[c for c in sliced["lineitem"].words.columns if c.startswith("quantity__")]).persist()
        held = SlicedTable(words, sliced["lineitem"].manifest)
        fast, slow = timed(f"q1_cached_{tag}", lambda: held.where("quantity > 25").count().collect(), 5, 2), timed(f"q1_cached_{tag}_scalar", lambda: baselines.scalar(q1, "quantity > 25").collect(), 5, 2)
        detail[f"q1_cached_{tag}_speedup"] = round(slow / fast, 2)
        q1.unpersist(), words.unpersist()
    last = f"{done[-1]:g}m"
    for s in done:
        detail[f"speedup_geometric_mean_{s:g}m"] = round(statistics.geometric_mean(detail[f"{q}_{s:g}m_speedup"] for q in PATTERNS), 2)
    value = sum(queries[f"{q}_{last}"] for q in PATTERNS)
    print(json.dumps({"metric": f"encoded scans q1-q5 over {done[-1]:g} million rows, sum of medians", "value": round(value, 4), "unit": "sec", "queries": {k: round(v, 4) for k, v in queries.items()}, "sf": sf_dir.rsplit("sf", 1)[-1], "detail": detail}))
    shutil.rmtree(root, ignore_errors=True)
    spark.stop()


if __name__ == "__main__":
    main()
