"""Sends a question to the method that the graph's size, degrees and the cost of a write call for."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from ..operators import blocks, connect, degree
from ..operators.oracles import BiconnectivityOracle, ConnectivityOracle
from .graph import CostMeter, Graph, choose_method
from .scratch import materialize

QUESTIONS = ("components", "bridges", "articulation", "two_edge")


@dataclass
class Answer:
    rows: DataFrame
    plan: dict


def solve(graph: Graph, question: str, omega: float, *, bound: int = 16, seed: int = 0, meter: CostMeter | None = None) -> Answer:
    """``components`` (vid, comp), ``bridges`` (a, b), ``articulation`` (vid) or ``two_edge`` (vid, comp) by the chosen family.

    Where the sparse family meets a degree above ``bound``, questions that an expanded graph can answer
    go there and come back in the original's names; articulation points go to the dense method."""
    if question not in QUESTIONS:
        raise ValueError(f"unknown question: {question}")
    n, m, widest = graph.vertices.count(), graph.edges.count(), graph.max_degree()
    plan = choose_method(n, m, omega, widest, bound)
    wide = widest > bound
    if plan["family"] == "sparse" and wide and question == "articulation":
        plan = {**plan, "family": "dense", "rerouted": "blocks do not outlive degree expansion"}
    if plan["family"] == "dense":
        return Answer(_dense(graph, question, plan["beta"], seed, meter), plan)
    if not wide:
        return Answer(_sparse(graph, question, max(2, plan["k"]), seed, meter), plan)
    expanded, names = degree.expand(graph, max(2, bound // 2), meter=meter)
    expanded, names = expanded.fixed("expanded"), materialize(names, "names")
    if question == "components":
        return Answer(degree.project_components(ConnectivityOracle.build(expanded, k=max(2, plan["k"]), seed=seed, meter=meter).component(), names), plan)
    cut = materialize(degree.project_edges(blocks.bridges(blocks.block_labelling(expanded, meter=meter, beta=0.5, seed=seed)), names), "expanded-bridges")
    if question == "bridges":
        return Answer(cut, plan)
    return Answer(connect.components_star(Graph(graph.vertices, graph.edges.join(cut, ["a", "b"], "left_anti"))), plan)


def _dense(graph: Graph, question: str, beta: float, seed: int, meter: CostMeter | None) -> DataFrame:
    beta = min(0.5, beta)
    if question == "components":
        return connect.components_lowwrite(graph, beta=beta, seed=seed, meter=meter)
    labelled = blocks.block_labelling(graph, beta=beta, seed=seed, meter=meter)
    return {"bridges": blocks.bridges, "articulation": blocks.articulation_points, "two_edge": blocks.two_edge_components}[question](labelled)


def _sparse(graph: Graph, question: str, k: int, seed: int, meter: CostMeter | None) -> DataFrame:
    if question == "components":
        return ConnectivityOracle.build(graph, k=k, seed=seed, meter=meter).component()
    oracle = BiconnectivityOracle.build(graph, k=k, seed=seed, meter=meter)
    if question == "bridges":
        return oracle.is_bridge().filter("is_bridge").select("a", "b")
    return oracle.is_articulation() if question == "articulation" else oracle.two_edge_components()
