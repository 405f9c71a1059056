"""The experiment workloads on this machine: writes edgemill/plans/timings.csv (read by the catalogue's queries) and prints it.

python experiments.py [workload...]; workloads: single, strong, weak, capped. Each run is a session of its own.
"""

from __future__ import annotations

import csv
import json
import os
import subprocess
import sys
import tempfile

ROOT = os.path.dirname(os.path.abspath(__file__))
FILE = os.path.join(ROOT, "edgemill", "plans", "timings.csv")
FIELDS = ["workload", "variant", "step", "scale", "nb", "cores", "seconds", "spilled_mb", "heap_mb"]

#: (workload, variant, scale, buckets, cores, heap in MB)
RUNS = (
    [("single", v, s, 8, 8, 6000) for s in (16, 18, 20) for v in ("ordered", "unordered")]
    + [("capped", "ordered", 18, 32, 4, 700)]
    + [("strong", "ordered", 16, 8, c, 6000) for c in (1, 2, 4, 8)]
    + [("weak", "ordered", s, 1 if s == 14 else 8, 1 << (s - 14), 6000) for s in (14, 16)]
)


def one(workload: str, variant: str, scale: int, nb: int, cores: int, heap: int) -> list[dict]:
    """One run in this process: a small one first, so that no step pays for starting up."""
    sys.path.insert(0, ROOT)
    from edgemill.config import GenSpec, Layout
    from edgemill.plans.generate import generate_graph
    from edgemill.session import build_session

    log = tempfile.mkdtemp(prefix="edgemill-events-")
    spark = build_session(
        "edgemill-experiment", f"local[{cores}]", spark__driver__memory=f"{heap}m", spark__ui__enabled="false", spark__sql__shuffle__partitions=str(max(nb, cores)), spark__ui__showConsoleProgress="false",
        spark__eventLog__enabled="true", spark__eventLog__dir=f"file://{log}", spark__eventLog__compress="false", spark__eventLog__rolling__enabled="false",
    )
    spark.sparkContext.setLogLevel("ERROR")
    generate_graph(spark, GenSpec(scale=10), Layout(1 << 10, min(nb, 8), 1), strategy="merge", csr=variant)
    run = generate_graph(spark, GenSpec(scale=scale), Layout(1 << scale, nb, 1), strategy="merge", csr=variant)
    spark.stop()
    spilled = 0
    for name in os.listdir(log):
        with open(os.path.join(log, name)) as f:
            for line in f:
                if line.startswith('{"Event":"SparkListenerTaskEnd"'):
                    spilled += (json.loads(line).get("Task Metrics") or {}).get("Disk Bytes Spilled", 0)
    return [dict(zip(FIELDS, (workload, variant, step, scale, nb, cores, round(s, 3), spilled >> 20, heap))) for step, s in run.seconds.items()]


def main(wanted: list[str]) -> None:
    kept: list[dict] = []
    if os.path.exists(FILE):
        with open(FILE, newline="") as f:
            kept = [r for r in csv.DictReader(f) if wanted and r["workload"] not in wanted]
    for run in RUNS:
        if wanted and run[0] not in wanted:
            continue
        out = subprocess.run([sys.executable, __file__, "--one", json.dumps(run)], capture_output=True, text=True, timeout=900)
        if out.returncode:
            print(out.stderr[-3000:], file=sys.stderr)
            raise SystemExit(f"{run} failed")
        rows = json.loads(out.stdout.strip().splitlines()[-1])
        print(run, {r["step"]: r["seconds"] for r in rows}, flush=True)
        kept += rows
        with open(FILE, "w", newline="") as f:
            writer = csv.DictWriter(f, FIELDS)
            writer.writeheader()
            writer.writerows(kept)


if __name__ == "__main__":
    if sys.argv[1:2] == ["--one"]:
        print(json.dumps(one(*json.loads(sys.argv[2]))))
    else:
        main(sys.argv[1:])
