"""Flow graphs: regular, input and output nodes; push, pull and blocking edges along the streaming direction."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

REGULAR, INPUT, OUTPUT = "regular", "input", "output"
PUSH, PULL, BLOCKING = "push", "pull", "blocking"


class FlowGraphError(ValueError):
    """A graph that breaks a rule; the message names the rule and the nodes."""


@dataclass(frozen=True)
class Node:
    name: str
    kind: str = REGULAR
    block: str | None = None  # the blocking component that this node is a half of


@dataclass(frozen=True)
class Edge:
    src: str
    dst: str
    kind: str = PUSH


@dataclass
class FlowGraph:
    nodes: list[Node] = field(default_factory=list)
    edges: list[Edge] = field(default_factory=list)

    def node(self, name: str, kind: str = REGULAR, block: str | None = None) -> FlowGraph:
        self.nodes.append(Node(name, kind, block))
        return self

    def blocking(self, name: str) -> FlowGraph:
        """Both halves of a blocking component, named name + i and name + o, and the edge between them."""
        self.nodes += [Node(f"{name}i", INPUT, name), Node(f"{name}o", OUTPUT, name)]
        self.edges.append(Edge(f"{name}i", f"{name}o", BLOCKING))
        return self

    def push(self, *names: str) -> FlowGraph:
        self.edges += [Edge(a, b, PUSH) for a, b in zip(names, names[1:], strict=False)]
        return self

    def pull(self, *names: str) -> FlowGraph:
        self.edges += [Edge(a, b, PULL) for a, b in zip(names, names[1:], strict=False)]
        return self

    @property
    def names(self) -> list[str]:
        return [n.name for n in self.nodes]

    def streaming(self) -> list[Edge]:
        return [e for e in self.edges if e.kind != BLOCKING]

    def reach(self) -> set[tuple[str, str]]:
        """(from, to): to can be reached from `from` over one edge or more, blocking ones included."""
        out = set()
        after: dict[str, list[str]] = {}
        for e in self.edges:
            after.setdefault(e.src, []).append(e.dst)
        for a in self.names:
            todo, seen = list(after.get(a, [])), set()
            while todo:
                b = todo.pop()
                if b not in seen:
                    seen.add(b)
                    todo += after.get(b, [])
            out |= {(a, b) for b in seen}
        return out

    def without(self, edge: Edge) -> FlowGraph:
        return replace(self, edges=[e for e in self.edges if e != edge], nodes=list(self.nodes))


def regrid_graph() -> FlowGraph:
    """The eight components of the regridding pipeline as ten nodes."""
    g = FlowGraph().node("src").node("map").blocking("S1").node("rd").node("co").blocking("S2").node("emit").node("wr")
    return g.push("src", "map", "S1i").push("rd", "co", "S2i").push("S2o", "emit", "wr").pull("S1o", "co")


def delay_graph() -> FlowGraph:
    """u pushes to a sorter and to w, w pulls the sorter: needs a delay."""
    return FlowGraph().node("u").blocking("S").node("w").push("u", "Si").push("u", "w").pull("So", "w")
