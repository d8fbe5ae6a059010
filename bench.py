"""Times the headline queries; prints one JSON line."""

import json
import os
import signal
import time

from pyspark.sql import SparkSession

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "4")
NAMES = ("inf_sage2", "win_tumbling_counts", "win_session_counts", "win_adaptive_counts", "msgs_layer2_streaming", "msgs_layer2_windowed", "volume_by_policy", "part_random_arith", "replication_factor", "sync_messages", "wl_w2_topic", "train_grad_2layer", "agg_mean_incremental")


PATIENCE = 240  # seconds for each of the two long parts; one that takes longer is reported as cut off


def within(seconds: int, part):
    """part(), or None where it takes longer."""

    def stop(*_):
        raise TimeoutError

    signal.signal(signal.SIGALRM, stop)
    signal.alarm(seconds)
    try:
        return part()
    except TimeoutError:
        return None
    finally:
        signal.alarm(0)


def incremental(spark) -> tuple[dict, dict]:
    """Batches of 2000 edges on the loaded purchase graph: kept up by deltas, and by what a static library does.

    20 edges stand for the per-event case. Each time is that of one batch, its results written out.
    """
    from deltamp.operators import infer
    from deltamp.operators.store import Store
    from deltamp.queries.traces import goods_of, recompute

    write = lambda rows: rows.write.format("noop").mode("overwrite").save()
    v, e = goods_of(spark, SF)
    n = e.count()
    cut = {k: e.where(f"pmod(xxhash64(seq, 1), {max(2, n // k)}) = 0") for k in (2000, 20)}
    base = infer.settle(e.join(cut[2000].select("seq"), "seq", "left_anti").join(cut[20].select("seq"), "seq", "left_anti"))
    took, began = {}, time.time()
    store = Store(spark, 2, 8).load(v, base)
    took["state_load"] = time.time() - began
    store.apply(1, base.limit(0))
    for k, (size, batch) in enumerate(cut.items(), 2):
        batch = infer.settle(batch)
        began = time.time()
        store.apply(k, batch)
        took[f"delta_{size}"] = time.time() - began
        began = time.time()
        write(recompute(v, e, batch))
        took[f"recompute_{size}"] = time.time() - began
    began = time.time()
    write(infer.full(v, e, 2))
    took["full_pass"] = time.time() - began
    took = {k: round(t, 3) for k, t in took.items()}
    return took, {f"{how}/delta, {k} edges": round(took[f"{how}_{k}"] / took[f"delta_{k}"], 2) for k in cut for how in ("recompute",)} | {f"full pass/delta, {k} edges": round(took["full_pass"] / took[f"delta_{k}"], 2) for k in cut}


def main() -> None:
    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "4g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    from deltamp.queries import QUERIES

    QUERIES["wl_w12_sweep"](spark, SF).collect()  # warm up
    took = {}
    for name in (n for n in NAMES if n != "volume_by_policy"):
        began = time.time()
        QUERIES[name](spark, SF).write.format("noop").mode("overwrite").save()
        took[name] = round(time.time() - began, 3)
    swapped = time.time()
    rows = within(PATIENCE, lambda: {(r["policy"], r["layer"]): r["bytes"] for r in QUERIES["volume_by_policy"](spark, SF).collect()})
    cut_off = [] if rows else ["volume_by_policy"]
    if rows:
        took["volume_by_policy"] = round(time.time() - swapped, 3)
    spark.sparkContext.cancelAllJobs()
    states, kept = within(PATIENCE, lambda: incremental(spark)) or ({}, {})
    cut_off += [] if states else ["incremental"]
    spark.sparkContext.cancelAllJobs()
    took |= states
    swaps = QUERIES["msgs_layer2_streaming"](spark, SF).first()[0], {r["hours"]: r["swaps"] for r in QUERIES["msgs_layer2_windowed"](spark, SF).collect()}
    ratios = {"swaps per_event/24h": round(swaps[0] / swaps[1][24], 2)} | kept
    if rows:
        ratios |= {f"layer {k} volume per_event/{p}": round(rows["per_event", k] / rows[p, k], 2) for p in ("tumbling", "session") for k in (1, 2)}
    print(json.dumps({"metric": "headline_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "ratios": ratios, "cut_off": cut_off, "sf": SF.rstrip("/").rpartition("sf")[2]}))


if __name__ == "__main__":
    main()
