"""Headline queries at BENCH_SF_DIR on local[BENCH_CPUS]; prints one JSON line. A batch of queries shares each run, and
seconds are those of the whole batch."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from proxcore import cores, exact, local  # noqa: E402
from proxcore.baselines import static  # noqa: E402
from proxcore.proximity import prepared, prox_hops  # noqa: E402
from proxcore.runtime import settle, sweep  # noqa: E402
from proxcore.session import session  # noqa: E402
from proxcore.sources.views import VIEWS  # noqa: E402
from proxcore.workloads import draw  # noqa: E402

SF, CPUS = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    spark = session(CPUS, int(CPUS))
    spark.sparkContext.setLogLevel("ERROR")
    seconds: dict[str, float] = {}

    def timed(name: str, make):  # noqa: ANN001, ANN202
        began = time.perf_counter()
        out = make()
        seconds[name] = round(time.perf_counter() - began, 3)
        print(name, seconds[name], file=sys.stderr, flush=True)
        return out

    g, states = timed("graph_copurchase_q1", lambda: prepared(VIEWS["copurchase_q1"](spark, SF)))
    st, q = settle(g.static), settle(draw(g, 50))
    prox = timed("proximity_50", lambda: settle(prox_hops(g, q, states=states)))
    weights = settle(cores.in_units(prox))
    timed("exact_from_proximity_50", lambda: settle(exact.from_weights(st, weights, q)))
    timed("exact_50", lambda: settle(exact.exact_community(g, q)))
    timed("local_50", lambda: settle(local.local_community(g, q)))
    timed("floor_kcore_50", lambda: settle(static.floor_kcore(g, q, k=2)))
    timed("static_core_50", lambda: settle(static.static_core(g, q)))
    timed("truss_50", lambda: settle(static.truss_community(g, q)))
    big, big_states = timed("graph_trade", lambda: prepared(VIEWS["trade"](spark, SF)))
    few = settle(big.static.select("v").distinct().orderBy("v").limit(5).selectExpr("v as q"))
    timed("proximity_trade_5_rounds", lambda: settle(prox_hops(big, few, states=big_states, most_rounds=5)))
    sweep(spark)
    spark.stop()
    print(json.dumps({"metric": "headline_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(SF.rstrip("/"))}))


if __name__ == "__main__":
    main()
