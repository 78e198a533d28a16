"""Measures: run times, candidates, ratios, reach."""

from __future__ import annotations

import statistics
import threading
import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame

from pathsieve.operators import baselines, udf_modes
from pathsieve.operators import levels as native
from pathsieve.plans.spec import GuardedPathQuery, plan


def median_seconds(run: Callable[[], DataFrame], runs: int = 3, warm_ups: int = 1) -> float:
    """Submit to full output, without transfer to the driver."""
    times = []
    for k in range(warm_ups + runs):
        began = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        if k >= warm_ups:
            times.append(time.perf_counter() - began)
    return statistics.median(times)


def reach(make: Callable[[int], DataFrame], lengths: range, timeout_s: float, context) -> tuple[int, dict[int, float]]:
    """(largest length that ends in time, seconds of each); a run that takes longer is cancelled."""
    seconds: dict[int, float] = {}
    for length in lengths:
        group, began = f"reach-{uuid.uuid4().hex}", time.perf_counter()
        context.setJobGroup(group, group, interruptOnCancel=True)
        timer = threading.Timer(timeout_s, context.cancelJobGroup, [group])
        timer.start()
        try:
            make(length).write.format("noop").mode("overwrite").save()
        except Exception:
            if time.perf_counter() - began < timeout_s:
                raise
            break
        finally:
            timer.cancel()
        seconds[length] = time.perf_counter() - began
    return max(seconds, default=0), seconds


def total_candidates(query: GuardedPathQuery, how: str = "early") -> int:
    run = {"early": native.candidates, "walk": lambda q: baselines.postfilter_walk(q, candidates=True), "trail": lambda q: baselines.postfilter_trail(q, candidates=True)}[how]
    return sum(r["n"] for r in run(query).collect())


def probed_edges(query: GuardedPathQuery) -> DataFrame:
    """(len, n): extensions that enter the check, at each hop."""
    p = plan(query)
    edges, rows = p.edges(), []
    for hop, prefixes in enumerate(native.frontiers(p), 1):
        if hop > query.max_len:
            break
        n = native.step(p, prefixes, edges, hop, probes=True).count()  # edges are read anew: the executor's are its own
        if n:
            rows.append((hop, n))
    return query.graph.edges.sparkSession.createDataFrame(rows, "len long, n long")


def function_share(query: GuardedPathQuery, runs: int = 3) -> dict[str, float]:
    """Seconds of the direct variant, of the native one, and the share that functions and their state's text take: what going native saves."""
    direct = median_seconds(lambda: udf_modes.run_levels(query, "json_udf"), runs)
    native_s = median_seconds(lambda: native.levels(query), runs)
    return {"direct": direct, "native": native_s, "share": max(0.0, 1 - native_s / direct)}


def function_breakdown(query: GuardedPathQuery) -> DataFrame:
    """(part, calls, seconds, share) of one run of the direct variant: each of the five functions, the JSON text around them, and all else (scans, joins, transfer). Seconds of workers are added up, so that on one core they are a part of the run time."""
    spark = query.graph.edges.sparkSession
    names = (*udf_modes.FUNCTIONS, "json")
    clock = udf_modes.Clock(spark, names)
    began = time.perf_counter()
    udf_modes.run_levels(query, "json_udf", clock=clock).collect()
    total = time.perf_counter() - began
    rows = [(n, clock.calls[n].value, clock.seconds[n].value) for n in names]
    rows.append(("rest", 0, max(0.0, total - sum(r[2] for r in rows))))
    whole = sum(r[2] for r in rows)
    return spark.createDataFrame([(*r, r[2] / whole) for r in rows], "part string, calls long, seconds double, share double")


def tightness(query: GuardedPathQuery) -> DataFrame:
    """One row: (candidates, answers)."""
    spark = query.graph.edges.sparkSession
    return spark.createDataFrame([(total_candidates(query), sum(r["n"] for r in native.levels(query).collect()))], "candidates long, answers long")


def reduction(query: GuardedPathQuery) -> DataFrame:
    """One row: (early, walk) candidates."""
    return query.graph.edges.sparkSession.createDataFrame([(total_candidates(query), total_candidates(query, "walk"))], "early long, walk long")


def walk_trail_gap(query: GuardedPathQuery) -> DataFrame:
    """(len, walk, trail, gap) of check-at-the-end engines."""
    walk = baselines.postfilter_walk(query, candidates=True).withColumnRenamed("n", "walk")
    trail = baselines.postfilter_trail(query, candidates=True).withColumnRenamed("n", "trail")
    return walk.join(trail, "len", "left").na.fill(0, ["trail"]).selectExpr("len", "walk", "trail", "walk - trail AS gap")


def assert_sound(query: GuardedPathQuery) -> None:
    """Early filtering loses no answer: the brute force gives the same counts. Small graphs only."""
    early = {r["len"]: r["n"] for r in native.levels(query).collect()}
    late = {r["len"]: r["n"] for r in baselines.postfilter_walk(query).collect()}
    if early != late:
        raise AssertionError(f"early {early}, brute force {late}")
