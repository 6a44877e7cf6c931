"""Bench: the paper's workloads on the given tables. Prints one JSON line.

BENCH_SF_DIR: tables (default /root/testdata/sf0.1); BENCH_CPUS: local cores (default 8). `queries` are whole: tables are
read, matrices converted, kernels run. `kernels` are pairs of a baseline and our form on cached graphs, `conversion` what
converting these graphs took once, `backends` one program on each back end, `ablation` one superstep under each strategy.
`--scaling` also runs the applications on 1, 2, 4 and 8 cores; `--grid FILE` appends runs of the strategies for the mapper."""

from __future__ import annotations

import json
import os
import sys
import time
from dataclasses import replace
from statistics import median

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = int(os.environ.get("BENCH_CPUS", "8"))
SF = os.path.basename(SF_DIR.rstrip("/")).removeprefix("sf")
#: Micro-benchmarks, applications with their datasets, and chains.
HEADLINE = ["gemv", "spmm", "gemm_block", "symm", "trmm", "add_union", "syrk", "app_force", "app_force_viscous", "app_force_fine", "app_energy", "app_energy_param", "app_energy_dense", "app_heat_3072", "app_heat_4096", "app_heat_5120", "chain_paths_orders", "chain_tree", "chain_dp", "chain_dp_back", "chain_vec", "gbmv_window", "mv_hub_split_equals", "mv_split_equals"]
BASELINES = {"base_force": "app_force", "base_energy": "app_energy", "chain_seq_back": "chain_dp_back", "chain_seq_orders": "chain_paths_orders", "mv_coarse": "mv_hub_split_equals", "comm_unmerged": "gemv"}
SCALED = ["app_force_fine", "app_energy", "app_heat_3072"]


def session(cores: int):
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master(f"local[{cores}]").appName("gamat-bench").config("spark.sql.shuffle.partitions", str(cores))
        .config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    return s


def seconds(spark, fn, runs: int) -> float:
    """Median seconds of warm runs; the rows are all computed and go nowhere."""
    out = []
    for k in range(runs + 1):
        began = time.time()
        fn(spark, SF_DIR).write.format("noop").mode("overwrite").save()
        if k:
            out.append(time.time() - began)
        if k and sum(out) > 20:
            break
    return round(median(out), 3)


class Graphs:
    """The matrices of the kernels, converted once."""

    def __init__(self, spark):
        from gamat.operators.cache import GraphCache
        from gamat.plans import queries_matrix as qm
        from gamat.plans import queries_relational as qr
        from gamat.sources import fixtures as fx

        self.cache, d = GraphCache(), SF_DIR
        made = {"mx1": fx.mx1, "mx2": fx.mx2, "mx3": fx.mx3, "mx5": fx.mx5, "mx8": fx.mx8, "mx13": fx.mx13, "mx4": fx.mx4}
        made |= {f"back{i}": lambda s, d, i=i: qm.series_back(s, d)[i] for i in range(4)}
        made |= {f"orders{i}": lambda s, d, i=i: qm.series_orders(s, d)[i] for i in range(4)}
        self.g = {n: self.cache.get_or_build(n, lambda f=f: f(spark, d), hub_degree=32) for n, f in made.items()}
        self.state = {n: replace(x, df=x.df.persist()) for n, x in (("mx1", fx.supplier_cents(spark, d)), ("mx2", fx.part_cents(spark, d)), ("mx3", fx.part_cents(spark, d)), ("mx5", fx.supplier_cents(spark, d)))}
        self.layers, self.velocity = qr.layers(spark), qr.velocity(spark, self.g["mx8"].meta.n_cols)
        self.layers = [replace(x, meta=replace(x.meta, nnz=x.meta.n_rows * x.meta.n_cols)) for x in self.layers]

    def conversion(self) -> dict[str, float]:
        return {n: round(e.seconds, 3) for n, e in self.cache.entries.items() if n.startswith("mx")}


def kernels(spark, g: Graphs) -> dict[str, list[float]]:
    """name: [baseline seconds, our seconds, speedup], on cached graphs."""
    from gamat.operators import apps, baselines, chain, ops
    from gamat.types import Strategy

    back, orders = ([g.g[f"{n}{i}"] for i in range(4)] for n in ("back", "orders"))
    energy = [g.g["mx13"], g.g["mx4"], *g.layers]
    mv = lambda name, **s: lambda *_: ops.mv(g.g[name], g.state[name], strategy=Strategy(**s)).df
    pairs = {
        "direct dependencies: order series": (lambda *_: chain.sequential(orders).edges, lambda *_: chain.paths(orders).edges),
        "cheapest order: supplier series": (lambda *_: chain.sequential(back).edges, lambda *_: chain.dp(back).edges),
        "potential energy": (lambda *_: baselines.sequential_chain(energy).edges, lambda *_: apps.potential_energy(*energy[:2], energy[2:])),
        "merge before send: order x part": (mv("mx3", merge=False), mv("mx3")),
        "hubs replicated: customer x part": (mv("mx2", merge=False, join="merge"), mv("mx2", hub_broadcast=32)),
        "fine-grained, merged, replicated: customer x part": (mv("mx2", merge=False, join="merge"), mv("mx2", join="broadcast")),
        "arbitrary form: part x supplier": (lambda *_: baselines.naive_cross(g.g["mx1"], g.state["mx1"]).df, mv("mx1", join="broadcast")),
    }
    out = {}
    for name, (base, ours) in pairs.items():
        b, o = seconds(spark, base, 1 if "arbitrary" in name else 3), seconds(spark, ours, 3)
        out[name] = [b, o, round(b / o, 2)]
    return out


def programs(spark, g: Graphs) -> tuple[dict[str, float], dict[str, float]]:
    """(one product per back end, one superstep per strategy): seconds on cached graphs."""
    from gamat.plans import backends, ir
    from gamat.types import CATALOGUE, Strategy

    program = ir.mv(ir.Load("mx1", g.g["mx1"]), ir.State("x", g.state["mx1"]))
    per = {b: seconds(spark, lambda *_, b=b: backends.emit(program, Strategy(backend=b, bucket=256)).df, 2) for b in ("S", "B", "V")}
    step = ir.mv(ir.Load("mx2", g.g["mx2"]), ir.State("x", g.state["mx2"]))
    return per, {n: seconds(spark, lambda *_, s=s: backends.emit(step, s).df, 2) for n, s in CATALOGUE.items() if s.backend == "S" and s.reorder == "none"}


def measures(g: Graphs) -> dict:
    """Rows and bytes shuffled with and without merging, and the share of time that matrix operations take in the kinetics."""
    from gamat.operators import metrics, ops
    from gamat.types import Strategy

    sent = {n: metrics.shuffled(ops.mv(g.g["mx3"], g.state["mx3"], strategy=Strategy(merge=m)).df) for n, m in (("merged", True), ("unmerged", False))}
    a = g.g["mx1"].where("dst < 3072")
    a = replace(a, meta=replace(a.meta, n_rows=min(3072, a.meta.n_rows)))
    t = ops.mm_dense(a, a.T, True)
    steps = {"read": (lambda: a.edges.select("dst", "src"), False), "temperatures": (lambda: t.edges, True), "step": (lambda: ops.mv(a, g.state["mx1"]).df, True)}
    return {"shuffled_rows_bytes": sent, "share": {n: round(x, 3) for n, x in metrics.shares(steps).items()}}


def grid(spark, path: str) -> None:
    """(op, matrix, platform, features, strategy, seconds) for the mapper: products of cached graphs under the strategies."""
    from gamat.operators import features, ops
    from gamat.types import CATALOGUE

    g = Graphs(spark)
    with open(path, "a") as f:

        def record(op, name, platform, strategy, fn) -> None:
            values = features.vector(features.profile(g.g[name]).first(), op, platform)
            f.write(json.dumps({"op": op, "matrix": f"{name}@{SF}", "platform": platform, "features": values, "strategy": strategy, "seconds": seconds(spark, fn, 2)}) + "\n")

        for name, x in g.state.items():
            for s in CATALOGUE.values():
                if s.backend == "S" and s.reorder == "none" and s.merge:
                    record("mv", name, "jvm", s.name, lambda *_, n=name, x=x, s=s: ops.mv(g.g[n], x, strategy=s).df)
        for name in ("mx1", "mx2", "mx4", "mx5"):
            a = g.g[name]
            for s, product in (("vertex_pull", ops.mm), ("dense_block", ops.mm_panel)):
                if s == "vertex_pull" or ops.fits(a.T):
                    record("mm", name, "jvm", s, lambda *_, a=a, p=product: p(a.T, a).edges)
        for name in ("mx1", "mx2"):
            for s, unit in (("edge_merge", "edge"), ("vertex_pull", "vertex")):
                record("add", name, "jvm", s, lambda *_, n=name, u=unit: ops.add(g.g[n], g.g[n], unit=u).edges)


def main() -> None:
    from gamat.plans import catalog

    spark = session(CPUS)
    if "--grid" in sys.argv:
        grid(spark, sys.argv[sys.argv.index("--grid") + 1])
        return
    times = {n: seconds(spark, catalog.QUERIES[n], 2) for n in [*HEADLINE, *BASELINES]}
    out = {"metric": "headline queries, sum of median warm seconds", "value": round(sum(times[n] for n in HEADLINE), 3), "unit": "sec", "queries": times, "sf": SF, "whole_queries": {f"{b} -> {q}": round(times[b] / times[q], 2) for b, q in BASELINES.items()}}
    g = Graphs(spark)
    out["kernels"] = kernels(spark, g)
    out["speedup"] = {n: x[2] for n, x in out["kernels"].items()}
    out["conversion"] = g.conversion()
    out["backends"], out["ablation"] = programs(spark, g)
    out["measures"] = measures(g)
    if "--scaling" in sys.argv:
        out["scaling"] = {}
        for cores in (1, 2, 4, 8):
            spark.stop()
            spark = session(cores)
            out["scaling"][cores] = {n: seconds(spark, catalog.QUERIES[n], 1) for n in SCALED}
    print(json.dumps(out))


if __name__ == "__main__":
    main()
