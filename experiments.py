"""The experiment tables of the README, from real runs.

    python experiments.py quality [sf_dir]     weight over that of global paths, and seconds
    python experiments.py sizes [sf_dir]       the same methods against n on random graphs
    python experiments.py threads [sf_dir]     seconds and doubling ratios over 1, 2, 4 .. threads
    python experiments.py phases [sf_dir]      survivors of the phases, also over the levels of a contraction
"""

from __future__ import annotations

import subprocess
import sys
import time
from collections.abc import Callable, Iterator

import bench

METHODS = ("heavy_edge", "local_max", "greedy", "global_paths", "red_blue")


def line(*cells: object) -> None:
    print("| " + " | ".join(str(c) for c in cells) + " |", flush=True)


def run_methods(edges) -> Iterator[tuple[str, int, float]]:
    """Weight and seconds of each method on a written edge table."""
    from matchloom.registry import METHODS as KNOWN

    for name in METHODS:
        began = time.time()
        weight = int(KNOWN[name](edges).weight())
        yield name, weight, time.time() - began


def table(spark, instances: dict[str, Callable]) -> None:
    from matchloom.storage import Scratch

    line("graph", "edges", *(f"{m} ratio, s" for m in METHODS))
    line(*["---"] * (2 + len(METHODS)))
    warm = False
    for name, build in instances.items():
        edges = Scratch(spark, "experiment").save(build(), "edges")
        if not warm:  # the first jobs of a session compile code
            list(run_methods(edges))
            warm = True
        found = {m: (w, s) for m, w, s in run_methods(edges)}
        best = found["global_paths"][0] or 1
        line(name, edges.count(), *(f"{found[m][0] / best:.4f}, {found[m][1]:.1f}" for m in METHODS))


def quality(spark, d: str) -> None:
    from matchloom.sources import graphs
    from matchloom.operators.coarsen import coarsen

    level = lambda k: coarsen(graphs.copurchase(spark, d), rating="expansion2", max_levels=k)[-1]["coarse"]
    table(spark, {
        "Delaunay, 2 of 64 dimensions": lambda: graphs.delaunay2d(spark, d), **{f"random, {a} draws": (lambda a=a: graphs.random_alpha(spark, d, a)) for a in (4, 16, 64)},
        "random geometric, lengths": lambda: graphs.rgg_events(spark, d), "random geometric, random weights": lambda: graphs.rgg_events(spark, d, True),
        "parts bought together": lambda: graphs.copurchase(spark, d), "the same, contracted once": lambda: level(1), "parts and suppliers": lambda: graphs.part_supp(spark, d),
        "parts of orders": lambda: graphs.order_part(spark, d), "successive users": lambda: graphs.event_succ(spark, d),
    })


def sizes(spark, d: str) -> None:
    from matchloom.sources import graphs

    table(spark, {f"random, n = 2^{k}, {a} draws": (lambda k=k, a=a: graphs.random_graph(spark, 1 << k, a)) for a in (4, 16) for k in (10, 12, 14, 16)})


def threads(spark, d: str, most: int = 8) -> None:
    spark.stop()
    line("graph", "threads", "seconds", "ratio", "speedup")
    line(*["---"] * 5)
    for name, build in (("random geometric, random weights", f"graphs.rgg_events(s, {d!r}, True)"), ("random, 64 draws", f"graphs.random_alpha(s, {d!r}, 64)")):
        before, first, p = None, None, 1
        while p <= most:
            code = (
                f"import bench; from matchloom.operators.localmax import local_max; from matchloom.sources import graphs; from matchloom.storage import Scratch\n"
                f"s = bench.session({p}); e = Scratch(s, 'b').save({build}); f = lambda *_: local_max(e, finish_rows=0).matching\n"
                f"bench.seconds(s, f, ''); print('T', bench.seconds(s, f, ''))"
            )
            out = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, timeout=900).stdout
            now = next(float(x[2:]) for x in out.splitlines() if x.startswith("T "))
            first = first or now
            line(name, p, f"{now:.1f}", f"{before / now:.2f}" if before else "", f"{first / now:.2f}")
            before, p = now, 2 * p


def phases(spark, d: str) -> None:
    from matchloom.operators.coarsen import coarsen
    from matchloom.operators.localmax import local_max
    from matchloom.sources import graphs

    line("graph", "edges", "phases", "mean share of edges left", "work over edges")
    line(*["---"] * 5)

    def show(name: str, log: list[dict]) -> None:
        if log:
            m = log[0]["live_before"]
            line(name, m, len(log), f"{sum(x['shrink'] for x in log) / len(log):.3f}", f"{sum(x['live_before'] for x in log) / m:.2f}")

    show("random geometric, random weights", local_max(graphs.rgg_events(spark, d, True)).log)
    show("random, 64 draws", local_max(graphs.random_alpha(spark, d, 64)).log)
    for x in coarsen(graphs.copurchase(spark, d), rating="expansion2", max_levels=4):
        show(f"parts bought together, level {x['level']}", x["log"])
    for x in coarsen(graphs.rgg_events(spark, d, True), rating="expansion2", max_levels=4):
        show(f"random geometric, level {x['level']}", x["log"])


if __name__ == "__main__":
    parts = {"quality": quality, "sizes": sizes, "threads": threads, "phases": phases}
    chosen = sys.argv[1] if len(sys.argv) > 1 else "quality"
    parts[chosen](bench.session(8), sys.argv[2] if len(sys.argv) > 2 else "/root/testdata/sf0.1")
