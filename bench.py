"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS].

Prints one JSON line with every entry that finished, whatever ends the run: the end of the entries, an interrupt, or a watchdog that
stops a run stuck beyond its budget. Entries run in the order of their importance; each has a time limit after which its jobs are
cancelled, and none starts when the whole budget is used up. Progress goes to the error output.
"""

from __future__ import annotations

import json
import os
import signal
import sys
import threading
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
os.environ.setdefault("SPARK_LOCAL_IP", "127.0.0.1")

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
BUDGET_S = float(os.environ.get("BENCH_BUDGET_S", "480"))
ENTRY_S = float(os.environ.get("BENCH_ENTRY_S", "90"))


class Bench:
    def __init__(self, spark):
        self.spark, self.start = spark, time.time()
        self.times: dict[str, float] = {}
        self.left_out: dict[str, str] = {}
        self.lock, self.printed = threading.Lock(), False
        signal.signal(signal.SIGINT, lambda *_: self.leave())
        signal.signal(signal.SIGTERM, lambda *_: self.leave())
        watchdog = threading.Timer(BUDGET_S + 2 * ENTRY_S, self.leave)
        watchdog.daemon = True
        watchdog.start()

    def result(self) -> None:
        with self.lock:
            if not self.printed:
                self.printed = True
                print(self.line(), flush=True)

    def leave(self) -> None:
        self.result()
        os._exit(0)

    def line(self) -> str:
        return json.dumps({"metric": "headline_total", "value": round(sum(self.times.values()), 3), "unit": "sec", "queries": self.times, "sf": SF_DIR.rsplit("sf", 1)[-1], "left_out": self.left_out})

    def run(self, name: str, f, timed: bool = True):
        """``f``'s result; its seconds are kept, and its jobs cancelled after ENTRY_S."""
        if time.time() - self.start > BUDGET_S:
            self.left_out[name] = "budget used up"
            return None
        watch = threading.Timer(ENTRY_S, self.spark.sparkContext.cancelAllJobs)
        watch.start()
        began, out = time.time(), None
        try:
            out = f()
            if timed:
                self.times[name] = round(time.time() - began, 3)
        except Exception as e:  # noqa: BLE001  an entry's failure must not lose the others' figures
            self.left_out[name] = f"{type(e).__name__} after {time.time() - began:.0f} s"
        finally:
            watch.cancel()
        print(name, self.times.get(name, self.left_out.get(name, "")), file=sys.stderr, flush=True)
        return out


def main() -> None:
    from flextensor import workloads
    from flextensor.baselines import kron, multilinear
    from flextensor.bounds import gaussian
    from flextensor.exec import passes
    from flextensor.fit import evaluate
    from flextensor.model import init_model
    from flextensor.queries import QUERIES
    from flextensor.sampling import balanced_sample
    from flextensor.session import local_session

    spark = local_session(CPUS, 16, os.environ.get("BENCH_MEMORY", "6g"))
    b = Bench(spark)

    # keyed and key-free gradients of the same 100 × 100 × 100 tensor
    def small():
        c = workloads.w10(spark, SF_DIR).distribute(int(CPUS))
        n = init_model(c, 3, 50, "ard")
        a = gaussian.adjoints(n, passes.suff_stats(c, n))[0]
        passes.gradient_pass(c, n, a)
        return c, n, a

    made = b.run("w10_prepare", small, False)
    if made:
        c, n, a = made
        b.run("w10_keyfree", lambda: passes.gradient_pass(c, n, a))
        b.run("w10_keyed_combined", lambda: passes.keyed_gradient(c, n, a, True).count())
        b.run("w10_keyed", lambda: passes.keyed_gradient(c, n, a).count())
        c.df.unpersist()

    # one outer iteration of each large-scale method on the bibliography stand-in of all words
    def bibliography():
        t = balanced_sample(workloads.w6(spark, SF_DIR, None)).distribute(int(CPUS))
        m = init_model(t, 3, 100, "ard")
        evaluate(t, m, lam_iter=1)
        return t, m, t.with_df(t.df.where("y > 0"))

    made = b.run("w6_build", bibliography)
    if made:
        t, m, ones = made
        b.run("w13_flexgp_iteration", lambda: evaluate(t, m, lam_iter=10))
        b.run("w13_sparse_cp_iteration", lambda: multilinear.sparse_cp_tables(ones, 3, 1))
        b.run("w13_blockkron_iteration", lambda: kron.fit_blockkron(ones, 3, 12, [min(40, x) for x in t.dims], 1, 4))
        t.df.unpersist()

    # one evaluation of the code-access stand-in, rank 3, by number of tasks
    made = b.run("w5_build", lambda: workloads.w5(spark, SF_DIR).distribute(int(CPUS)))
    if made:
        k = init_model(made, 3, 100, "ard")
        evaluate(made, k)
        b.run("w9_iteration", lambda: evaluate(made, k))
        for tasks in (4, 2, 1):
            part = made.distribute(tasks)
            b.run(f"w9_iteration_{tasks}_tasks", lambda part=part: evaluate(part, k))
            part.df.unpersist()
    for q in ("q_build_w3", "q_build_w5", "q_build_w7", "q_suff_stats", "q_words", "q_asof", "st_tumbling"):
        b.run(q, lambda q=q: QUERIES[q](spark, SF_DIR).write.format("noop").mode("overwrite").save())
    b.result()


if __name__ == "__main__":
    main()
