"""How much a user writes: source lines of each vertex program (without blanks and comments)."""

from __future__ import annotations

import inspect

from vertexalg.algorithms.bfs import BfsProgram
from vertexalg.algorithms.cf import GradientProgram
from vertexalg.algorithms.components import ComponentsProgram
from vertexalg.algorithms.degrees import DegreeProgram
from vertexalg.algorithms.pagerank import PageRankProgram
from vertexalg.algorithms.sssp import SsspProgram
from vertexalg.algorithms.triangles import IntersectProgram, NeighborListProgram

PROGRAMS = {"degree": (DegreeProgram,), "rank": (PageRankProgram,), "bfs": (BfsProgram,), "sssp": (SsspProgram,), "triangles": (NeighborListProgram, IntersectProgram), "cf": (GradientProgram,), "components": (ComponentsProgram,)}


def lines(thing: object) -> int:
    rows = [x.strip() for x in inspect.getsource(thing).split("\n")]
    return sum(bool(x) and not x.startswith(("#", '"""')) for x in rows)


def effort() -> dict[str, int]:
    return {name: sum(lines(c) for c in classes) for name, classes in PROGRAMS.items()}
