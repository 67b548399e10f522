"""From movements to the summarized multi-level graph: aggregate, keep significant nodes, filter edges."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from ..config import PyramidConfig
from ..operators.aggregate import edges_of_flows, fine_flows, nodes_of_flows, pyramid_edges, pyramid_nodes
from ..operators.bloom import bloom_filter_edges, join_filter_edges
from ..operators.summarize import significant_nodes
from ..sources.shared import materialize


@dataclass
class GraphSet:
    nodes: DataFrame
    edges: DataFrame
    kept_nodes: DataFrame
    kept_edges: DataFrame


def build(movements: DataFrame, cfg: PyramidConfig = PyramidConfig(), tree=None) -> GraphSet:
    """The three steps. What several of them read is a table in the shared folder: the flows between finest cells, from which nodes
    and edges of all levels are summed, the nodes, and the kept nodes; all are bounded by the grid and the flows, not the movements.

    edge_filter: bloom gives the edges that pass the filters' membership test, the method's own output, in which few edges of
    nodes that were not kept remain; exact sends what passed through the semi-joins as well, which then shuffle only survivors;
    join and broadcast are the baselines.
    """
    if cfg.aggregation == "rollup":
        flows = materialize(fine_flows(movements, cfg))
        nodes, edges = materialize(nodes_of_flows(flows, cfg)), edges_of_flows(flows, cfg)
    else:
        nodes, edges = materialize(pyramid_nodes(movements, cfg)), pyramid_edges(movements, cfg)
    kept = materialize(significant_nodes(nodes, cfg, tree=tree))
    if cfg.edge_filter == "bloom":
        final = bloom_filter_edges(edges, kept, cfg.fpp)
    elif cfg.edge_filter == "exact":
        final = join_filter_edges(bloom_filter_edges(edges, kept, cfg.fpp), kept)
    else:
        final = join_filter_edges(edges, kept, "broadcast" if cfg.edge_filter == "broadcast" else None)
    return GraphSet(nodes, edges, kept, final)
