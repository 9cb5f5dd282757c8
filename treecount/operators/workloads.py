"""The experiment workloads: runs of the counting modes over graphs, templates and block numbers, timed and measured.

Block numbers stand for workers: a session cannot change its cores, so the volume each block count
moves is reported beside the seconds.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.templates import TreeTemplate
from ..sources import graphs as G
from . import counting as C
from . import exchange as E
from . import model as M

COLUMNS = "workload string, graph string, template string, mode string, p int, s int, colorful string, requests long, seconds double"


@dataclass(frozen=True)
class Run:
    """One timed count: a mode on a graph with p blocks and tasks of s neighbours."""

    graph: str
    template: str
    mode: str
    p: int = 4
    s: int = 50
    how: tuple = field(default=())


def _graph(spark: SparkSession, d: str, name: str) -> G.EdgeGraph:
    if name.startswith("rmat"):
        _, scale, edges, skew = name.split("_")
        raw = G.edges_of(G.rmat(spark, int(scale), int(edges), int(skew)))
    else:
        raw = G.graph(spark, d, name).edges
    return G.EdgeGraph(E.written(raw, "edges"))


def execute(spark: SparkSession, d: str, workload: str, runs: list[Run]) -> DataFrame:
    """A row a run: the count, the vertices asked for across blocks, and the seconds of the action."""
    graphs: dict[str, G.EdgeGraph] = {}
    asked: dict[tuple, int] = {}
    out = []
    for r in runs:
        if r.graph not in graphs:
            graphs[r.graph] = _graph(spark, d, r.graph)
        g = graphs[r.graph]
        if (r.graph, r.p) not in asked:
            asked[r.graph, r.p] = E.build_requests(g.edges, r.p).count()
        how = dict(r.how)
        if r.mode in ("staged", "adaptive", "adaptive_split", "local_remote", "static_slots"):
            how["blocks"] = r.p
        if r.mode == "adaptive_split":
            how["s"] = r.s
        began = time.time()
        row = C.colorful_count(g, TreeTemplate.named(r.template), [1], mode=r.mode, count_type="decimal" if r.mode != "replicated" else "long", **how).first()
        out.append((workload, r.graph, r.template, r.mode, r.p, r.s, str(row["colorful"]), asked[r.graph, r.p], time.time() - began))
    return spark.createDataFrame(out, COLUMNS)


def _grid(graphs, templates, modes, blocks=(4,), sizes=(50,), **how) -> list[Run]:
    return [Run(g, t, m, p, s, tuple(how.items())) for g in graphs for t in templates for m in modes for p in blocks for s in sizes]


#: Runs of each workload, by the figure or table they follow.
WORKLOADS: dict[str, list[Run]] = {
    "w1_bulk_growing_templates": _grid(["page_link"], ["u3-1", "u5-2", "u7-2", "u10-2"], ["bulk"], (4, 8)),
    "w2_strong_scaling_bulk_staged": _grid(["page_link"], ["u7-2"], ["bulk", "staged"], (4, 8)),
    "w4_adaptive_against_staged": _grid(["page_link"], ["u3-1", "u5-2"], ["staged", "adaptive"], (10,)),
    "w5_weak_scaling_rmat": _grid(["rmat_8_1000_3"], ["u5-2"], ["staged"], (4,)) + _grid(["rmat_9_2000_3"], ["u5-2"], ["staged"], (8,)),
    "w6_list_splitting_by_skew": _grid(["rmat_9_3000_1", "rmat_9_3000_3", "rmat_9_3000_8"], ["u5-2"], ["bulk", "adaptive_split"]),
    "w7_threads": _grid(["page_link"], ["u5-2"], ["bulk", "adaptive_split"], (2, 8)),
    "w9_task_size": _grid(["page_link"], ["u5-2"], ["adaptive_split"], (4,), (10, 50, 1000)),
    "w11_overall": _grid(["page_link"], ["u3-1", "u5-2", "u7-2"], ["adaptive_split", "resident_bulk"]),
    "w13_strong_scaling_skewed": _grid(["page_link"], ["u5-2"], ["adaptive_split", "resident_bulk"], (8, 16)),
}


def run(spark: SparkSession, d: str, workload: str) -> DataFrame:
    """The runs of a workload; ``speedup`` is over the fewest blocks of the same mode, graph and template."""
    x = execute(spark, d, workload, WORKLOADS[workload])
    return M.speedups(x.withColumn("key", F.concat_ws("/", "graph", "template", "mode", "s")), "key").drop("key")


def overlap(spark: SparkSession, d: str, graph: str, template: str, p: int) -> DataFrame:
    """(step, rho): measured overlap of each ring step in the last neighbour sums of a staged count."""
    g = _graph(spark, d, graph)
    t = TreeTemplate.named(template)
    leaf = C.init_counts(E.written(C.assign_colors(g.nodes(), t.k, [1]), "colors"))
    spans: list = []
    C.sums_staged(leaf, g.edges, p, spans=spans)
    return M.measured_rho(spark.createDataFrame(spans, "step int, kind string, start double, finish double"))


def shares(spark: SparkSession, runs: DataFrame, blocks: int = 4, alpha: float = 1e-4, beta: float = 1e-9) -> DataFrame:
    """(template, comm_share): modelled share of transfer in the run time of the templates of some runs, by their requests."""
    rows = []
    for r in runs.select("template", "p", "requests").distinct().collect():  # a row a run
        steps = M.totals(M.model_steps(spark, TreeTemplate.named(r["template"]), r["requests"], r["requests"] * r["p"], r["p"], beta, alpha, beta))
        x = steps.agg(F.sum("comm").alias("comm"), F.sum("comp").alias("comp")).first()
        rows.append((r["template"], r["p"], x["comm"] / (x["comm"] + x["comp"])))
    return spark.createDataFrame(rows, "template string, p int, comm_share double")
