"""Times of the headline queries; one JSON line. BENCH_SF_DIR and BENCH_CPUS say where and on how many cores."""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession

HERE = os.path.dirname(os.path.abspath(__file__))
os.environ["PYTHONPATH"] = os.pathsep.join([HERE, *filter(None, [os.environ.get("PYTHONPATH")])])


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "4")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", str(max(4, int(cpus)))).config("spark.driver.memory", "6g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from galoislake.operators import central
    from galoislake.plans import measures, rounds
    from galoislake.sources.workloads import WORKLOADS

    contexts = {w: WORKLOADS[w].context(spark, sf_dir) for w in ("lineitem_profile", "part_traits", "session_mix", "session_keys", "document_meta", "embedding_signs")}
    seconds, detail = {}, {}

    def run(name: str, make) -> None:
        got = measures.timed(make)
        seconds[name] = round(got["elapsed_s"], 3)
        detail[name] = {"rounds": got["rounds"], "intents": got["intents"], "seeds": got["seeds"], "per_s": round(got["intents"] / got["elapsed_s"], 1)}

    run("warm_up", lambda: rounds.round_all(contexts["document_meta"]))
    began = time.time()
    run("build_and_mine_lineitem_profile", lambda: rounds.round_all(WORKLOADS["lineitem_profile"].context(spark, sf_dir)))
    for w, ctx in contexts.items():
        run(f"round_all_{w}", lambda c=ctx: rounds.round_all(c))
        run(f"round_branch_{w}", lambda c=ctx: rounds.round_branch(c))
    run("round_single_20_rounds_lineitem_profile", lambda: rounds.round_single(contexts["lineitem_profile"], 3, max_rounds=20))
    run("round_all_reload_session_mix", lambda: rounds.round_all(contexts["session_mix"], static="reload"))
    for n in (1, 3, 9):
        run(f"round_all_{n}_parts_lineitem_profile", lambda k=n: rounds.round_all(contexts["lineitem_profile"], parts=k))
    for w in ("lineitem_profile", "session_mix"):
        for name, scan in (("lectic_scan", central.lectic_scan), ("branch_scan", central.branch_scan)):
            t = time.time()
            n = scan(contexts[w]).count()
            seconds[f"{name}_{w}"] = round(time.time() - t, 3)
            detail[f"{name}_{w}"] = {"intents": n}
    seconds.pop("warm_up")
    print(json.dumps({"metric": "headline_queries_seconds", "value": round(time.time() - began, 3), "unit": "sec", "queries": seconds, "detail": detail, "sf": sf_dir}))
    spark.stop()


if __name__ == "__main__":
    sys.exit(main())
