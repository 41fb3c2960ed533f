"""The hub summary graph: hubs, the pairs with a part between them, and summaries; zooming and rendering."""

from __future__ import annotations

import json
import math
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubloom.operators.graph import PropertyGraph
from hubloom.operators.scope import induced, induced_union


@dataclass
class HubSummaryGraph:
    vertices: DataFrame
    pairs: DataFrame
    tables: dict[str, DataFrame]
    hubs: list[int]
    graph: PropertyGraph | None = None
    vtags: DataFrame | Callable[[], DataFrame] | None = None  # or how to make them
    hops: int | None = None

    @property
    def edges(self) -> DataFrame:
        """One row a pair; a summary by groups is an ordered list of its rows."""
        out = self.pairs
        for name, table in self.tables.items():
            values = [c for c in table.columns if c not in ("x", "y")]
            single = len(values) == 1
            flat = table if single else table.groupBy("x", "y").agg(F.sort_array(F.collect_list(F.struct(*values))).alias(name.replace("+", "_")))
            out = out.join(flat.withColumnsRenamed({"x": "_x", "y": "_y"}), F.col("x").eqNullSafe(F.col("_x")) & F.col("y").eqNullSafe(F.col("_y")), "left").drop("_x", "_y")
        return out

    def to_tables(self) -> dict[str, DataFrame]:
        return {"vertices": self.vertices, "pairs": self.pairs, **self.tables}

    def validate(self, reachable: DataFrame) -> None:
        """Every pair is reachable, and every reachable pair of hubs is there."""
        both = self.pairs.exceptAll(reachable).union(reachable.exceptAll(self.pairs))
        if not both.isEmpty():
            raise ValueError("pairs and reachability disagree")

    # -- navigation: tags are known, so a zoom is a filter --------------------------
    def _tags(self) -> DataFrame:
        if callable(self.vtags):
            self.vtags = self.vtags()
        return self.vtags

    def zoom_edge(self, x: int, y: int) -> PropertyGraph:
        return induced(self.graph, self._tags(), self.hubs, x, y)

    def zoom_vertices(self, some: list[int]) -> PropertyGraph:
        return induced_union(self.graph, self._tags(), self.hubs, some)

    def diff(self, other: HubSummaryGraph, name: str) -> DataFrame:
        """Rows of a summary that are in one of two results only, with the side they are on."""
        a, b = self.tables[name], other.tables[name]
        return a.exceptAll(b).withColumn("side", F.lit("left")).unionByName(b.exceptAll(a).withColumn("side", F.lit("right")))

    # -- presentation -----------------------------------------------------------------
    def render(self, mode: str = "data", modes: dict[tuple[int, int], str] | None = None) -> dict | DataFrame:
        """``data``: rows for 2-D tables; ``graph``: a node-link payload; ``modes`` sets the form edge by edge."""
        if mode == "data" and not modes:
            return self.edges
        if mode not in ("data", "graph"):
            raise ValueError(f"unknown mode: {mode}")
        rows = [json.loads(r[0]) for r in self.edges.select(F.to_json(F.struct("*"), {"ignoreNullFields": "false"})).collect()]  # hundreds at most
        places = circular_layout(self.hubs)
        nodes = [{"id": h, "x": places[h][0], "y": places[h][1]} for h in self.hubs]
        for node, row in zip(nodes, self._attributes(), strict=False):
            node |= {"attributes": row}
        return {"nodes": nodes, "links": [self._link(r, (modes or {}).get((r["x"], r["y"]), mode)) for r in rows]}

    def _attributes(self) -> list[dict]:
        by_id = {r["vid"]: r for r in (json.loads(x[0]) for x in self.vertices.select(F.to_json(F.struct("*"))).collect())}
        return [by_id.get(h, {}) for h in self.hubs]

    @staticmethod
    def _link(row: dict, mode: str) -> dict:
        parts = {k: v for k, v in row.items() if k not in ("x", "y")}
        shape = {}
        for name, value in parts.items():
            if not isinstance(value, list):
                shape[name] = {"label": value}
            elif value and isinstance(value[0], dict):
                shape[name] = {"table": value} if mode == "data" else {"graph": _node_link(value)}
            else:
                shape[name] = {"list": value} if mode == "data" else {"chain": list(zip(value, value[1:], strict=False))}
        width = next((v for k, v in parts.items() if "strength" in k and isinstance(v, float)), 1.0)
        label = " ".join(str(v) for v in parts.values() if isinstance(v, str | int))
        return {"source": row["x"], "target": row["y"], "width": width, "label": label, "on_hover": "show_label", "summaries": shape}

    def to_dot(self) -> str:
        payload = self.render("graph")
        lines = [f'  "{n["id"]}";' for n in payload["nodes"]]
        lines += [f'  "{e["source"]}" -> "{e["target"]}" [label="{e["label"]}", penwidth={max(0.5, 4 * e["width"]):.2f}];' for e in payload["links"]]
        return "digraph hubs {\n" + "\n".join(lines) + "\n}\n"

    def write(self, path: str, fmt: str = "parquet") -> None:
        for name, table in self.to_tables().items():
            table.write.format(fmt).save(f"{path}/{name.replace('+', '_')}")


def _node_link(rows: list[dict]) -> dict:
    """An aggregate graph as nodes and links: rows with both ends are links, others nodes."""
    nodes, links = [], []
    for r in rows:
        ends = [k for k in r if k.startswith(("src_", "tgt_"))]
        (links if ends else nodes).append(r)
    return {"nodes": nodes, "links": links}


def circular_layout(hubs: list[int], radius: float = 1.0) -> dict[int, tuple[float, float]]:
    n = max(1, len(hubs))
    return {h: (round(radius * math.cos(2 * math.pi * i / n), 6), round(radius * math.sin(2 * math.pi * i / n), 6)) for i, h in enumerate(hubs)}


@dataclass
class ExplorationSession:
    """Queries one after another, back and forward; results keep their tags."""

    history: list[HubSummaryGraph] = field(default_factory=list)
    at: int = -1

    def push(self, result: HubSummaryGraph) -> HubSummaryGraph:
        self.history = [*self.history[: self.at + 1], result]
        self.at += 1
        return result

    @property
    def current(self) -> HubSummaryGraph:
        return self.history[self.at]

    def back(self) -> HubSummaryGraph:
        self.at = max(0, self.at - 1)
        return self.current

    def forward(self) -> HubSummaryGraph:
        self.at = min(len(self.history) - 1, self.at + 1)
        return self.current
