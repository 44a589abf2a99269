"""Cost measures of runs: counters, time, stored bytes, peak memory, and ratios between miners."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

from canopy.mine.result import MiningResult


def heap_pools(spark: SparkSession) -> list:
    pools = spark.sparkContext._jvm.java.lang.management.ManagementFactory.getMemoryPoolMXBeans()
    return [p for p in pools if p.getType().toString() == "Heap memory"]


def reset_peak(spark: SparkSession) -> None:
    """Start a new peak in the driver's JVM, which in local mode is the executor's as well."""
    spark.sparkContext._jvm.java.lang.System.gc()
    for pool in heap_pools(spark):
        pool.resetPeakUsage()


def peak_mb(spark: SparkSession) -> int:
    """The peak of this JVM's heap since ``reset_peak``, or the highest peak an executor has reported."""
    own = sum(p.getPeakUsage().getUsed() for p in heap_pools(spark)) >> 20
    executors = spark.sparkContext._jsc.sc().statusStore().executorList(True)
    reported = [0]
    for k in range(executors.size()):
        peaks = executors.apply(k).peakMemoryMetrics()
        if peaks.isDefined() and executors.apply(k).id() != "driver":
            reported.append(int(peaks.get().getMetricValue("JVMHeapMemory")) >> 20)
    return max(own, *reported) if executors.size() > 1 else own


def row(workload: str, result: MiningResult, memory_mb: int | None = None) -> dict:
    c = result.counters
    return {
        "workload": workload,
        "miner": result.miner,
        "strategy": result.search.options.strategy,
        "minsup": result.search.options.minsup,
        **{k: getattr(c, k) for k in ("computed", "freq", "lclosed", "lmax", "closed", "maximal", "occ_rows", "stored_bytes")},
        "seconds": round(c.seconds, 2),
        "closed_share": round(c.closed_seconds / c.seconds, 3) if c.seconds else 0.0,
        "peak_mb": memory_mb,
    }


def ratios(rows: list[dict], base: str) -> Iterator[dict]:
    """Time and counters of the other miners relative to ``base`` on the same workload, minsup and strategy."""
    of = {(r["workload"], r["minsup"], r["strategy"], r["miner"]): r for r in rows}
    for r in rows:
        b = of.get((r["workload"], r["minsup"], r["strategy"], base))
        if b is not None and r is not b:
            yield {
                "workload": r["workload"],
                "minsup": r["minsup"],
                "miner": r["miner"],
                "against": base,
                "speedup": round(r["seconds"] / max(b["seconds"], 1e-9), 2),
                "computed": round(r["computed"] / max(b["computed"], 1), 2),
                "stored": round(r["stored_bytes"] / max(b["stored_bytes"], 1), 2),
            }


def frame(spark: SparkSession, rows: list[dict]) -> DataFrame:
    names = "workload string, miner string, strategy string, minsup long, computed long, freq long, lclosed long, lmax long, closed long, maximal long, occ_rows long, stored_bytes long, seconds double, closed_share double, peak_mb int"
    return spark.createDataFrame([tuple(r.values()) for r in rows], names)
