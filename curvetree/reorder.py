"""``python -m curvetree.reorder --in CLOUD --out INDEX --curve hilbert``: order a cloud once, keep it for all searches."""

from __future__ import annotations

import argparse

from .operators.reorder import build_index, save_index
from .session import local_session


def main() -> None:
    args = argparse.ArgumentParser(prog="curvetree.reorder")
    args.add_argument("--in", dest="source", required=True, help="Parquet with pid, x, y, z")
    args.add_argument("--out", required=True)
    args.add_argument("--curve", default="hilbert", choices=("morton", "hilbert"))
    args.add_argument("--bucket", type=int, default=128)
    args.add_argument("--tile-points", type=int, default=4_000_000)
    a = args.parse_args()
    spark = local_session()
    save_index(build_index(spark.read.parquet(a.source), a.curve, a.bucket, a.tile_points), a.out)


if __name__ == "__main__":
    main()
