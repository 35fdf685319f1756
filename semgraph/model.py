"""Plain objects of a query: nodes, edges, graphs, sub-queries, parameters; and the table contracts."""

from __future__ import annotations

import json
from dataclasses import dataclass, field, replace
from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import types as T

KG_NODES = T.StructType([
    T.StructField("node_id", T.LongType()), T.StructField("name", T.StringType()),
    T.StructField("types", T.ArrayType(T.StringType())), T.StructField("attrs", T.MapType(T.StringType(), T.StringType())),
])
KG_EDGES = T.StructType([T.StructField("src", T.LongType()), T.StructField("predicate", T.StringType()), T.StructField("dst", T.LongType())])
PREDICATE_VECTORS = T.StructType([T.StructField("predicate", T.StringType()), T.StructField("vec", T.ArrayType(T.DoubleType()))])
LIBRARY = T.StructType([T.StructField(n, T.StringType()) for n in ("surface", "canonical", "target", "relation")])


@dataclass(frozen=True)
class KG:
    """A graph; `memo` holds what was derived from it once: its search index and its library."""

    nodes: DataFrame
    edges: DataFrame
    memo: dict = field(default_factory=dict, compare=False, repr=False)


@dataclass(frozen=True)
class QueryNode:
    """A specific node has a name; a target has types only; neither is a wildcard."""

    key: str
    types: tuple[str, ...] = ()
    name: str | None = None

    @property
    def specific(self) -> bool:
        return self.name is not None


@dataclass(frozen=True)
class QueryEdge:
    a: str
    b: str
    predicate: str


@dataclass(frozen=True)
class QueryGraph:
    nodes: tuple[QueryNode, ...]
    edges: tuple[QueryEdge, ...]
    label: str = ""

    def node(self, key: str) -> QueryNode:
        return next(n for n in self.nodes if n.key == key)

    def validate(self) -> QueryGraph:
        keys = [n.key for n in self.nodes]
        if len(set(keys)) != len(keys):
            raise ValueError("two query nodes have the same key")
        if not self.edges or any(e.a not in keys or e.b not in keys for e in self.edges):
            raise ValueError("an edge needs two nodes of the query")
        if not any(n.specific for n in self.nodes) or all(n.specific for n in self.nodes):
            raise ValueError("a query needs a specific node and a target")
        seen, todo = {keys[0]}, [keys[0]]
        while todo:
            at = todo.pop()
            for e in self.edges:
                for x, y in ((e.a, e.b), (e.b, e.a)):
                    if x == at and y not in seen:
                        seen.add(y)
                        todo.append(y)
        if seen != set(keys):
            raise ValueError("the query graph is not connected")
        return self

    @staticmethod
    def from_json(text: str | dict[str, Any]) -> QueryGraph:
        d = json.loads(text) if isinstance(text, str) else text
        nodes = tuple(QueryNode(n["key"], tuple(n.get("types") or ()), n.get("name")) for n in d["nodes"])
        return QueryGraph(nodes, tuple(QueryEdge(e["a"], e["b"], e["predicate"]) for e in d["edges"]), d.get("label", "")).validate()

    def to_json(self) -> str:
        return json.dumps({
            "label": self.label, "nodes": [{"key": n.key, "types": list(n.types), "name": n.name} for n in self.nodes],
            "edges": [{"a": e.a, "b": e.b, "predicate": e.predicate} for e in self.edges],
        })


@dataclass(frozen=True)
class SubQuery:
    """A path of query nodes from a specific node; `pivot_pos` is the place of the pivot on it (1 = after the first edge)."""

    sub_id: int
    path: tuple[QueryNode, ...]
    predicates: tuple[str, ...]
    pivot_pos: int

    @property
    def stages(self) -> int:
        return len(self.predicates)


@dataclass(frozen=True)
class Params:
    """Parameters of a search; defaults are those of the experiments."""

    k: int = 100
    tau: float = 0.8
    max_hops: int = 4
    hop_scope: str = "match"  # or query_edge: max_hops for each query edge
    revisit: str = "simple_path"  # or dominance, on_discovery
    bound: str = "standard"  # or tight
    m_mode: str = "predset"  # or scan, loose
    use_estimate: bool = True
    static_cut: bool = True
    topk_prune: bool = False
    through_target: bool = False
    weight_floor: float = 0.0
    rescale: str | None = None
    fetch_factor: int = 2
    relations: tuple[str, ...] = ("identical", "synonym", "abbreviation")
    batch: int = 1000
    eager: bool = True  # store every round; otherwise one lazy plan

    def but(self, **changes: Any) -> Params:
        return replace(self, **changes)

    def root(self, sub: SubQuery) -> int:
        """The degree of the root in estimates: the longest match."""
        return self.max_hops * (sub.stages if self.hop_scope == "query_edge" else 1)
