"""Headline queries, timed: prints one JSON line. BENCH_SF_DIR and BENCH_CPUS choose data and cores."""

from __future__ import annotations

import json
import os
import sys
import time

from kernmill.functions import points
from kernmill.functions.kernels import linear
from kernmill.operators import baselines, engines
from kernmill.plans.layout import LoopSpec, StoreSpec
from kernmill.session import build
from kernmill.sources.store import materialize


def fixed(source: str, k: int, engine: str = "mixed_15d", sweeps: int = 20, kernel=None, store: dict | None = None, **options):
    def run(sets):
        return engines.fit(sets[source], k, kernel, engine, loop=LoopSpec(max_iter=sweeps, fixed=True), store=StoreSpec(**(store or {})), **options)

    return run


SETS = {
    "emb": lambda s, d: points.emb(s, d),
    "wide28_4000": lambda s, d: points.sampled(points.wide28(s, d), 4000),
    "wide28_2000": lambda s, d: points.sampled(points.wide28(s, d), 2000),
    "docbag_2000": lambda s, d: points.sampled(points.docbag(s, d, 10_000), 2000),
}


def headline() -> dict:
    """Fits on point sets that are built before and timed by themselves."""
    wide, small, bags = "wide28_4000", "wide28_2000", "docbag_2000"
    return {
        "emb_k10_mixed_converged": lambda sets: engines.fit(sets["emb"], 10),
        "wide28_4000_k16_mixed_20": fixed(wide, 16),
        "wide28_4000_k16_mixed_f32_20": fixed(wide, 16, store={"dtype": "f32"}),
        "wide28_4000_k16_panel_20": fixed(wide, 16, "panel_1d"),
        "wide28_4000_k16_regrid_20": fixed(wide, 16, "regrid_h1d"),
        "wide28_4000_k16_tile2d_20": fixed(wide, 16, "tile_2d"),
        "wide28_4000_k16_window_20": fixed(wide, 16, "window", height=1024),
        "wide28_4000_k16_fused_20": fixed(wide, 16, "fused", height=512),
        "wide28_4000_k64_mixed_20": fixed(wide, 64),
        "wide28_2000_k16_entries_1": fixed(small, 16, "entries", 1),
        "wide28_2000_k16_mixed_1": fixed(small, 16, sweeps=1),
        "docbag_2000_k16_mixed_10": fixed(bags, 16, sweeps=10),
        "docbag_2000_k16_window_10": fixed(bags, 16, "window", sweeps=10, height=1024),
        "lloyd_wide28_4000_k16_20": lambda sets: baselines.lloyd(sets[wide], 16, LoopSpec(max_iter=20, fixed=True)),
        "lift_wide28_4000_k16_20": lambda sets: baselines.lift(sets[wide], 16, loop=LoopSpec(max_iter=20, fixed=True)),
        "linear_emb_k10_mixed": lambda sets: engines.fit(sets["emb"], 10, linear()),
    }


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = build("bench", int(os.environ.get("BENCH_CPUS", "8")))
    spark.sparkContext.setLogLevel("ERROR")
    engines.fit(points.mini(spark), 2)  # starts Python workers
    took, sets = {}, {}
    for name, source in SETS.items():
        began = time.time()
        sets[name] = materialize(source(spark, sf_dir))
        took[f"points_{name}"] = round(time.time() - began, 3)
    for name, run in headline().items():
        began = time.time()
        run(sets)
        took[name] = round(time.time() - began, 3)
        print(name, took[name], file=sys.stderr)
    print(json.dumps({"metric": "headline_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": sf_dir.rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    main()
