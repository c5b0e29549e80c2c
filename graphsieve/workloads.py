"""Templates of the workloads, and the graphs and answers that queries share within a session."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from graphsieve.operators.reduce import LabeledGraph
from graphsieve.operators.sieve import Solution, sieve
from graphsieve.plans.template import Template
from graphsieve.sources.graphs import LABELLED, RMAT, build

_made: dict = {}


def star(labels: str, edges) -> Template:
    return Template.build(labels.split("|"), edges)


_FOUR_CYCLE = [(0, 1), (1, 2), (2, 3), (3, 0)]
_TOPO = "STANDARD|PROMO|SMALL|LARGE|ECONOMY|MEDIUM"
_TOPO_C = [*_FOUR_CYCLE, (0, 4), (4, 5), (0, 5)]
#: Graph and template. Shapes that the reference only draws are our own, with the properties that it states.
WORKLOADS: dict[str, tuple[str, Template]] = {
    "w2": ("trade", Template.parse("(o:order:F)-(p:part:PROMO)-(s:supplier), (o)-(s)")),
    "w3": ("session", Template.parse("(a:click)-(b:view)-(c:purchase)-(d:click)")),
    # two 4-cliques that share a triangle
    "w4": ("coorder_typed", star("STANDARD|PROMO|SMALL|LARGE|MEDIUM", [(0, 1), (0, 2), (1, 2), (0, 3), (1, 3), (2, 3), (0, 4), (1, 4), (2, 4)])),
    "w4_unlabelled": ("lattice", Template.unlabelled([(0, 1), (0, 2), (1, 2), (0, 3), (1, 3), (2, 3), (0, 4), (1, 4), (2, 4)])),
    "w5": ("trade", star("order:P|cust:BUILDING|nation|supplier|order:P", [(0, 1), (1, 2), (2, 3), (3, 4)])),
    "w6": ("trade", star("order:F|part:PROMO|supplier|cust:BUILDING|nation", [(0, 1), (1, 2), (0, 2), (0, 3), (3, 4), (4, 2)])),
    "w7": ("trade", star("order:F|cust:BUILDING|nation|supplier|part:PROMO|region", [*_FOUR_CYCLE, (0, 4), (2, 5)])),
    # the shape of w7 with rare labels
    "w8": ("trade_fine", star("order:F|rich|nation|supplier|brand:Brand#4|region", [*_FOUR_CYCLE, (0, 4), (2, 5)])),
    # the most frequent labels
    "w9": ("trade", star("order:P|part:MEDIUM|order:O|supplier|order:F", [(0, 1), (1, 2), (0, 3), (2, 3), (1, 4), (3, 4)])),
    "w12": ("conv", star("conv|user|assistant|user", [(0, 1), (0, 2), (0, 3), (1, 2), (2, 3)])),
    "w12_session": ("session", star("user|click|error", [(0, 1), (0, 2), (1, 2)])),
    "w13": ("docs", star("source|en|en|source", [(0, 1), (1, 2), (2, 3)])),
    "topo_a": ("coorder_typed", star("STANDARD|PROMO|SMALL|LARGE", _FOUR_CYCLE)),
    "topo_b": ("coorder_typed", star("STANDARD|ECONOMY|MEDIUM", [(0, 1), (1, 2), (0, 2)])),
    "topo_c": ("coorder_typed", star(_TOPO, _TOPO_C)),
    "topo_d": ("coorder_typed", star(_TOPO, [*_TOPO_C, (0, 2)])),
    "topo_e": ("coorder_typed", star(_TOPO, [*_TOPO_C, (0, 2), (1, 3)])),
    "randlab_q4": ("random25", star("L0|L1|L2|L1", [(0, 1), (1, 2), (2, 3)])),
    "randlab_q6": ("random50", star("L0|L1|L2|L3", _FOUR_CYCLE)),
    "randlab_q8": ("random100", star("L0|L1|L2|L3|L4", [(0, 1), (1, 2), (2, 3), (3, 0), (3, 4)])),
    "knn_q4": ("knn", star("v7|v3|v7", [(0, 1), (1, 2)])),
    "rank_q4": ("session_ranked", star("R1|R2|R3|R1", [(0, 1), (1, 2), (2, 3)])),
    "rank_q6": ("session_ranked", star("R1|R2|R6|R3", [(0, 1), (1, 2), (0, 2), (1, 3), (2, 3)])),
    "rank_q7": ("session_ranked", star("R1|R2|R6|R3", [(0, 1), (1, 2), (0, 2), (1, 3)])),
    "rank_q8": ("session_ranked", star("R1|R2|R6|R3|R4", [(0, 1), (1, 2), (0, 2), (1, 3), (2, 3), (3, 4), (2, 4)])),
    "road_star5": ("lattice", Template.unlabelled([(0, 1), (0, 2), (0, 3), (0, 4)])),
    "road_c4": ("lattice", Template.unlabelled([(a, b) for b in range(4) for a in range(b)])),
    "road_c3": ("lattice", Template.unlabelled([(0, 1), (0, 2), (1, 2)])),
    "road_uq4": ("lattice", Template.unlabelled([(0, 1), (1, 2), (2, 3)])),
    "exists_none": ("trade", star("region|order:F", [(0, 1)])),
    # labels and directions of edges
    "shipped": ("shipped", Template.parse("(o:order:F)-[R]->(p:part:PROMO)-[from]->(s:supplier), (o)-[F]->(s)")),
    "against": ("shipped", Template.parse("(p:part:PROMO)->(o:order:F)")),
}
for _k in RMAT:
    WORKLOADS[f"{_k}_q4"] = _k, star("d4|d5|d6|d4", [(0, 1), (1, 2), (2, 3)])
    # seven roles of different labels: a triangle with four more
    WORKLOADS[f"{_k}_seven"] = _k, star("d5|d6|d7|d4|d3|d8|d2", [(0, 1), (1, 2), (0, 2), (1, 3), (3, 4), (2, 5), (0, 6)])

#: Relaxed level by level: an order's four partners, and six brands.
CLIQUE4 = ("trade", Template.build(["order:F", "part:PROMO", "supplier", "cust:BUILDING"], [(a, b) for a in range(4) for b in range(a)]))
CLIQUE6 = ("coorder_branded", Template.build([f"Brand#{k}" for k in (4, 2, 19, 8, 17, 16)], [(a, b) for a in range(6) for b in range(a)]))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _stamp(spark: SparkSession, sf_dir: str) -> tuple:
    """Names, lengths and times of the files, so that a folder that is written anew is read anew."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(sf_dir)
    fs = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    return tuple((s.getPath().getName(), s.getLen(), s.getModificationTime()) for s in fs.listStatus(where))


def once(spark: SparkSession, sf_dir: str, key: tuple, make):
    """Made once for each session and state of a folder: graphs and answers that several queries read."""
    key = (spark.sparkContext.applicationId, sf_dir, _stamp(spark, sf_dir), *key)
    if key not in _made:
        _made[key] = make()
    return _made[key]


def forget(kind: str | None = None) -> None:
    """What was made goes: all, or the answers ("solution") alone."""
    for k in [k for k in _made if kind is None or k[3] == kind]:
        del _made[k]


def graph(spark: SparkSession, sf_dir: str, name: str, t: Template | None = None) -> LabeledGraph:
    """The stored graph. With a template: the stored one if there is one, else, if that can be told apart, its edges that the template's may be."""
    whole = spark.sparkContext.applicationId, sf_dir, _stamp(spark, sf_dir), "graph", name
    if t is not None and t.edges and name in LABELLED and whole not in _made:
        return build(spark, sf_dir, name, t)
    return once(spark, sf_dir, whole[3:], lambda: build(spark, sf_dir, name))


def solution(spark: SparkSession, sf_dir: str, w: str) -> Solution:
    name, t = WORKLOADS[w]
    return once(spark, sf_dir, ("solution", w), lambda: sieve(graph(spark, sf_dir, name, t), t))
