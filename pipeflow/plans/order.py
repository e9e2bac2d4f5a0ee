"""Orders of the hooks inside a phase."""

from __future__ import annotations

from pipeflow.plans.graph import PULL, PUSH, FlowGraph
from pipeflow.plans.validate import topological


def describe(g: FlowGraph, phase: list[str]) -> list[str]:
    """Metadata flows along every edge: plain topological order."""
    inside = set(phase)
    return topological(phase, [(e.src, e.dst) for e in g.edges if e.src in inside and e.dst in inside])[0]


def open(g: FlowGraph, phase: list[str]) -> list[str]:  # noqa: A001
    """A receiver of a push edge opens before its sender, a source of a pull edge before its reader."""
    inside = set(phase)
    return topological(phase, [(e.dst, e.src) if e.kind == PUSH else (e.src, e.dst) for e in g.streaming() if e.src in inside and e.dst in inside])[0]


def close(g: FlowGraph, phase: list[str]) -> list[str]:
    return open(g, phase)[::-1]


def initiators(g: FlowGraph, phase: list[str]) -> list[str]:
    """Nodes that nobody pushes to and nobody pulls from: they drive the phase."""
    inside = set(phase)
    driven = {e.dst for e in g.edges if e.kind == PUSH and e.dst in inside} | {e.src for e in g.edges if e.kind == PULL and e.src in inside}
    return [n for n in phase if n not in driven]
