"""The experiment workloads as runs: seconds (median of repeats), blocks, peak heap, recall. `python -m flowblocks.experiments`
prints one JSON line for each run; WORKLOADS names them. A run that passes its timeout is reported as such."""
from __future__ import annotations

import json
import os
import statistics
import sys
import time

from pyspark.sql import SparkSession

from .durable import durable
from .operators import cells as C
from .plans import approx, mine, rank
from .queries import net

TIMEOUT = 180.0
SHAPES = [(2, 2, 2), (2, 2, 3), (2, 2, 4), (3, 3, 3), (4, 4, 3)]


def _heap(spark: SparkSession, reset: bool = False) -> int:
    """Peak MB of the heap pools of the driver's JVM; in local mode that is the whole process."""
    pools = [p for p in spark._jvm.java.lang.management.ManagementFactory.getMemoryPoolMXBeans() if str(p.getType()) == "Heap memory"]
    if reset:
        spark._jvm.System.gc()
        for p in pools:
            p.resetPeakUsage()
        return 0
    return sum(p.getPeakUsage().getUsed() for p in pools) >> 20


def measure(spark, run, repeats: int = 1) -> dict:
    """run() -> a frame, or (frame, extra figures)."""
    took, extra, n = [], {}, None
    for _ in range(repeats):
        _heap(spark, True)
        began = time.time()
        try:
            out = run()
            out, extra = out if isinstance(out, tuple) else (out, {})
            n = out.count()
        except TimeoutError:
            return {"seconds": None, "timeout": TIMEOUT}
        took.append(time.time() - began)
    return {"seconds": round(statistics.median(took), 2), "patterns": n, "peak_heap_mb": _heap(spark), **extra}


class Runs:
    def __init__(self, spark, sf_dir, repeats=1):
        self.spark, self.sf_dir, self.repeats, self._nets = spark, sf_dir, repeats, {}

    def hot(self, name, s_a):
        if name not in self._nets:
            self._nets[name] = net(self.spark, self.sf_dir, name)
        cells, g, slots = self._nets[name]
        return durable(C.hot(cells, s_a)), g, slots

    def say(self, workload, run, **params):
        print(json.dumps({"workload": workload, **params, **measure(self.spark, run, self.repeats)}), flush=True)

    def exact(self, workload, name, s_a, s_r, mode, bounds):
        hot, g, slots = self.hot(name, s_a)

        def run():
            found = mine.enumerate_blocks(hot, g, slots, s_r, mode, bounds, timeout_s=TIMEOUT)
            total = {k: sum(x.get(k) or 0 for x in found.stats) for k in ("generated", "probes", "bound_prunes", "memo_hits")}
            return found.df, {**total, "prepare_s": round(sum(x["generate_s"] for x in found.stats), 2), "admit_s": round(sum(x["count_s"] for x in found.stats), 2)}

        self.say(workload, run, net=name, s_a=s_a, s_r=s_r, mode=mode, bounds=bounds)

    def by_heat(self, name="freight", heats=("0.01", "0.05"), modes=mine.MODES, bounds=(3, 3, 3)):
        """Runtime, breakdown, counts and memory by s_a for every mode."""
        for s_a in heats:
            for mode in modes:
                self.exact("by_heat", name, s_a, "0.5", mode, bounds)

    def by_density(self, name="freight", ratios=("0.4", "0.5", "0.6", "0.7"), modes=("plain", "memo_skip_nbr", "packed")):
        for s_r in ratios:
            for mode in modes:
                self.exact("by_density", name, "0.02", s_r, mode, (3, 3, 3))

    def by_bound(self, modes=("plain", "memo_skip_nbr", "full")):
        for side in range(3):
            for b in (1, 2, 3):
                for mode in modes:
                    self.exact("by_bound", "freight", "0.02", "0.5", mode, tuple(b if i == side else 2 for i in range(3)))

    def ranking(self, levels=(5, 6, 7, 8), ks=(50, 100, 300), modes=("plain", "full", "threshold")):
        hot, g, slots = self.hot("freight", "0.1")
        for k, last in [(300, x) for x in levels] + [(k, 7) for k in ks]:
            for mode in modes:
                self.say("ranking", lambda k=k, last=last, mode=mode: rank.enumerate_top(hot, g, slots, k, last, mode)[0], k=k, max_level=last, mode=mode)

    def approximate(self, heats=("0.02", "0.05", "0.1"), ratios=("0.3", "0.4"), shapes=SHAPES, draws=1512, keep=137):
        """Exact, uniform and weighted blocks of one shape, with what is common and the ceiling of the pools."""
        cases = [(a, "0.5", (2, 2, 2)) for a in heats] + [("0.1", r, (2, 2, 2)) for r in ratios] + [("0.1", "0.5", s) for s in shapes[1:]]
        for s_a, s_r, shape in cases:
            hot, g, slots = self.hot("freight", s_a)
            exact = durable(mine.exact_shape(hot, g, slots, s_r, shape))
            po, pd, _ = approx.pools(self.spark, g, slots, shape)
            most = approx.ceiling(exact, po, pd).count()
            self.say("approximate", lambda: mine.exact_shape(hot, g, slots, s_r, shape), method="exact", s_a=s_a, s_r=s_r, shape=shape)  # noqa: B023
            for method, run in (("uniform", lambda: approx.uniform(hot, g, slots, s_r, shape, draws)[0]), ("weighted", lambda: approx.weighted(hot, g, slots, s_r, shape, keep))):  # noqa: B023
                def both(run=run, exact=exact, most=most):
                    found = durable(run())
                    a = approx.accuracy(found, exact).first()
                    return found, {"exact": a.n_exact, "common": a.n_common, "ceiling": most}

                self.say("approximate", both, method=method, s_a=s_a, s_r=s_r, shape=shape)


WORKLOADS = ("by_heat", "by_density", "by_bound", "ranking", "approximate")


def main(names) -> None:
    cpus, sf_dir = os.environ.get("BENCH_CPUS", "8"), os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.01")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    runs = Runs(spark, sf_dir, int(os.environ.get("BENCH_REPEATS", "1")))
    mine.enumerate_blocks(*runs.hot("freight", "0.01"), "0.5", "full", (2, 2, 2)).df.count()  # warm
    for name in names or WORKLOADS:
        getattr(runs, name)()


if __name__ == "__main__":
    main(sys.argv[1:])
