"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line, also when some of them fail or it is told to end."""

from __future__ import annotations

import json
import os
import signal
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
os.environ.setdefault("PYTHONPATH", sys.path[0])

SIZES = (1, 10, 25, 100, 250, 1000, 2500, 10000)
#: Seconds after which no further part is begun.
ENOUGH = float(os.environ.get("BENCH_SECONDS", "1500"))


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    from veilmatch.operators import cost, match, quality, score, secure
    from veilmatch.operators.registry import Registry
    from veilmatch.plans import catalog

    folder = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "16g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    times: dict[str, float] = {}
    failed: dict[str, str] = {}
    extra: dict[str, object] = {}
    start = time.perf_counter()

    def report(code: int | None = None, *_) -> None:
        if code is not None:
            failed["rest"] = "ended from outside"
        print(json.dumps({"metric": "link_all", "value": times.get("link_all"), "unit": "sec", "queries": times, "failed": failed, "sf": folder.rstrip("/").rpartition("sf")[2], **extra}), flush=True)
        if code is not None:
            os._exit(128 + code)

    signal.signal(signal.SIGTERM, report)

    def timed(name, frame) -> None:
        if time.perf_counter() - start > ENOUGH:
            failed[name] = "not begun: out of time"
            return
        began = time.perf_counter()
        try:
            frame().write.format("noop").mode("overwrite").save()
            times[name] = round(time.perf_counter() - began, 3)
        except Exception as error:  # the other figures still count
            failed[name] = str(error)[:300]

    registry = Registry.of(spark, folder)
    timed("registry", lambda: registry.truth)  # builds and writes both sides
    timed("encode_left", lambda: score.encode(registry.left))
    timed("encode_right", lambda: score.encode(registry.right))
    x, y = catalog.ex(spark, folder), catalog.ey(spark, folder)
    n, m = x.count(), y.count()
    one, sizes = x.where("rec_id = 10000000"), [k for k in SIZES if k <= m]
    first = lambda k: y.where(F.col("rec_id") < 20_000_000 + k)
    # The whole link is timed before anything keeps its result.
    timed("link_all", lambda: match.link_all(x, y, 7000))
    for k in sizes:
        timed(f"link_one_{k}", lambda: match.link_all(one, first(k), 7000))  # noqa: B023
    for k in sizes:
        timed(f"private_link_one_{k}", lambda: secure.link_all(one, first(k), 7000))  # noqa: B023
    side = min(n, 500)
    timed(f"private_link_{side}x{side}", lambda: secure.link_all(x.where(F.col("rec_id") < 10_000_000 + side), first(side), 7000))
    timed("lossless_links", lambda: match.lossless_links(x, y, 7000))
    timed("error_sweep", lambda: quality.sweep(match.best_partners(x, y), catalog.truth(spark, folder)))
    if "link_all" in times:
        extra |= {"pairs": n * m, "pairs_per_second": round(n * m / times["link_all"])}
    if f"private_link_{side}x{side}" in times:
        extra["private_pairs_per_second"] = round(side * side / times[f"private_link_{side}x{side}"])
    # Measured compute plus the network of the closed forms, against the published seconds.
    modelled = {(r["profile"], r["size"]): r for r in cost.modelled(spark, compute=0.0).collect()}
    for k in sizes:
        if f"private_link_one_{k}" in times:
            for p in "ABC":
                r = modelled[p, k]
                extra[f"with_network_{p}_{k}"] = [round(r["seconds"] + times[f"private_link_one_{k}"], 2), r["published_seconds"]]
    report()
    spark.stop()


if __name__ == "__main__":
    main()
