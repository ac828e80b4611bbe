"""Timing measures: repeated runs, speedup, thread sweeps, times relative to scan-only."""

from __future__ import annotations

import json
import os
import statistics
import subprocess
import sys
import time
from collections.abc import Callable
from pathlib import Path

from pyspark.sql import DataFrame

ROOT = Path(__file__).resolve().parent.parent.parent


def consume(df: DataFrame) -> None:
    """Run a plan to its end without keeping its rows."""
    df.write.format("noop").mode("overwrite").save()


def time_runs(make: Callable[[], DataFrame], n: int = 10, warm: int = 1) -> dict:
    """Mean, deviation and all of n timed runs after `warm` untimed ones."""
    for _ in range(warm):
        consume(make())
    took = []
    for _ in range(n):
        began = time.perf_counter()
        consume(make())
        took.append(time.perf_counter() - began)
    return {"mean_s": statistics.mean(took), "sd_s": statistics.pstdev(took), "runs": took}


def speedup(one: float, many: float) -> float:
    return one / many


def thread_sweep(names: list[str], cores: list[int], sf_dir: str, runs: int = 3) -> list[dict]:
    """Each query on local[c] for every c, each c in a process of its own; speedup is over the first c."""
    out, first = [], {}
    for c in cores:
        code = (
            "import json,sys;sys.path.insert(0,%r);from spanwalk.session import local_session;from spanwalk.workloads.measures import time_runs;import __spark_entry__ as e;"
            "s=local_session(%d,%d);s.sparkContext.setLogLevel('ERROR');q=e.queries();print('TIMES'+json.dumps({n:time_runs(lambda:q[n](s,%r),%d)['mean_s'] for n in %r}))"
        ) % (str(ROOT), c, max(2, c), sf_dir, runs, names)
        said = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, env=os.environ | {"PYTHONPATH": str(ROOT)}).stdout
        found = json.loads(said.rpartition("TIMES")[2])
        for name, s in found.items():
            first.setdefault(name, s)
            out.append({"query": name, "cores": c, "seconds": round(s, 3), "speedup": round(speedup(first[name], s), 2)})
    return out


def normalized(times: dict[str, float], base: str = "scan") -> dict[str, float]:
    return {k: v / times[base] for k, v in times.items()}
