"""Run the experiments and print their tables as Markdown: python experiments.py [sf_dir] [seconds a cell may take]."""

from __future__ import annotations

import sys


def main(args: list[str]) -> None:
    import verify
    from bipercolate.plans import experiments
    from bipercolate.shipping import ship

    spark = ship(verify.session("8"))
    found = experiments.report(spark, args[0] if args else "/root/testdata/sf0.01", float(args[1]) if args[1:] else 120)
    for name, table in found.items():
        rows = table.collect()
        print(f"\n## {name}\n\n| {' | '.join(table.columns)} |\n|{'---|' * len(table.columns)}")
        for r in rows:
            print("| " + " | ".join(f"{x:.4g}" if isinstance(x, float) else str(x) for x in r) + " |", flush=True)
    spark.stop()


if __name__ == "__main__":
    main(sys.argv[1:])
