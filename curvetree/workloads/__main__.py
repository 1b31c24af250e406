"""Run workloads and write one CSV each."""

from __future__ import annotations

import argparse
import csv
from pathlib import Path

from ..session import local_session
from .experiments import WORKLOADS, Bench


def main() -> None:
    args = argparse.ArgumentParser(prog="curvetree.workloads")
    args.add_argument("--sf-dir", required=True)
    args.add_argument("--only", default="")
    args.add_argument("--out", default="/tmp/curvetree-workloads")
    args.add_argument("--cores", type=int, default=8)
    args.add_argument("--runs", type=int, default=1)
    args.add_argument("--one", help="cloud:structure:radius:centres (a number or all), for the scaling workload: prints seconds")
    a = args.parse_args()
    bench = Bench(local_session(a.cores, max(8, 4 * a.cores)), a.sf_dir, tile_points=2000 if a.one else 50_000, runs=a.runs)
    if a.one:
        name, structure, r, n = a.one.split(":")
        bench.radius(name, structure, "sphere", float(r), 100)  # builds the index, starts the workers
        print(bench.radius(name, structure, "sphere", float(r), None if n == "all" else int(n))["seconds"])
        return
    Path(a.out).mkdir(parents=True, exist_ok=True)
    for name in a.only.split(",") if a.only else WORKLOADS:
        rows = WORKLOADS[name](bench)
        names = [*dict.fromkeys(k for r in rows for k in r)]
        with open(f"{a.out}/{name}.csv", "w", newline="") as f:
            out = csv.DictWriter(f, names)
            out.writeheader()
            out.writerows(rows)
        print(name, len(rows), "rows", flush=True)


main()
