"""Programs as trees: vertex and neighbour loops whose bodies assign or reduce properties.

Frozen dataclasses, compared by value.  ``Program`` holds declarations; the builders of the library
at the end are the programs that the analyses and tests speak about.
"""

from __future__ import annotations

from dataclasses import dataclass, field


class Node:
    """Anything in a program tree."""


# expressions ---------------------------------------------------------------------------------


@dataclass(frozen=True)
class Lit(Node):
    value: float


@dataclass(frozen=True)
class Ref(Node):
    """A loop variable, edge variable or scalar."""

    name: str


@dataclass(frozen=True)
class Prop(Node):
    """Property ``name`` of the vertex that ``var`` stands for."""

    var: str
    name: str


@dataclass(frozen=True)
class EProp(Node):
    """Property ``name`` of an edge variable."""

    edge: str
    name: str


@dataclass(frozen=True)
class Bin(Node):
    op: str
    left: Node
    right: Node


@dataclass(frozen=True)
class Call(Node):
    name: str
    args: tuple[Node, ...]


@dataclass(frozen=True)
class EdgeOf(Node):
    """The edge between two vertices, to be searched for."""

    v: str
    nbr: str


# statements ----------------------------------------------------------------------------------


@dataclass(frozen=True)
class Let(Node):
    name: str
    value: Node


@dataclass(frozen=True)
class Assign(Node):
    target: Prop | EProp
    value: Node


@dataclass(frozen=True)
class Reduce(Node):
    op: str
    target: Prop | EProp
    value: Node


@dataclass(frozen=True)
class GlobalReduce(Node):
    op: str
    name: str
    value: Node


@dataclass(frozen=True)
class If(Node):
    cond: Node
    then: Block
    otherwise: Block | None = None
    by_owner: bool = False


@dataclass(frozen=True)
class Block(Node):
    body: tuple[Node, ...] = ()


@dataclass(frozen=True)
class ForVertices(Node):
    var: str
    body: Block
    where: Node | None = None


@dataclass(frozen=True)
class ForNeighbors(Node):
    var: str
    of: str
    body: Block
    direction: str = "out"


@dataclass(frozen=True)
class ForLevels(Node):
    root: int
    body: Block
    reverse: bool = False


@dataclass(frozen=True)
class WhileWorklist(Node):
    body: Block


@dataclass(frozen=True)
class FixedPoint(Node):
    var: str
    cond: Node
    body: Block
    max_iter: int = 100


# made by rewrites only -----------------------------------------------------------------------


@dataclass(frozen=True)
class ForIncident(Node):
    """Loop over the edges of ``of``; ``edge`` is the edge and ``var`` its far end."""

    edge: str
    var: str
    of: str
    body: Block
    direction: str = "out"


@dataclass(frozen=True)
class Emit(Node):
    op: str
    target: Prop | EProp
    value: Node
    combine: bool = False
    local: str = "queue"  # or "apply" at once


@dataclass(frozen=True)
class Sync(Node):
    how: str = "all_to_all"


@dataclass(frozen=True)
class LocalFixpoint(Node):
    body: Block
    max_rounds: int | None = None


@dataclass(frozen=True)
class DirectGet(Node):
    """An operand read without a lock; ``residency`` says when: always, or if its owner is the reader."""

    operand: Node
    residency: str


@dataclass(frozen=True)
class Program:
    """Declarations and body.  ``vprops`` and ``eprops`` map names to (type, initial value)."""

    name: str
    body: Block
    vprops: dict = field(default_factory=dict)
    eprops: dict = field(default_factory=dict)
    seeds: tuple = ()  # (property, vertex id or None for all, value)

    def vprop(self, name: str, kind: str = "long", init=None) -> Program:
        return Program(self.name, self.body, {**self.vprops, name: (kind, init)}, self.eprops, self.seeds)

    def eprop(self, name: str, kind: str = "long", init=None) -> Program:
        return Program(self.name, self.body, self.vprops, {**self.eprops, name: (kind, init)}, self.seeds)

    def set(self, prop: str, vertex: int | None, value) -> Program:
        return Program(self.name, self.body, self.vprops, self.eprops, (*self.seeds, (prop, vertex, value)))


def children(n: Node) -> list[Node]:
    """Direct sub-trees, in program order."""
    out = []
    for v in vars(n).values() if not isinstance(n, Program) else [n.body]:
        if isinstance(v, Node):
            out.append(v)
        elif isinstance(v, tuple):
            out += [x for x in v if isinstance(x, Node)]
    return out


def walk(n: Node):
    yield n
    for c in children(n):
        yield from walk(c)


# library -------------------------------------------------------------------------------------


def _worklist(name: str, value: Node, op: str = "min", search: bool = False, extra: tuple[Node, ...] = ()) -> Program:
    edge = (Let("e", EdgeOf("v", "n")),) if search else ()
    body = Block((WhileWorklist(Block((ForVertices("v", Block((ForNeighbors("n", "v", Block((*edge, Reduce(op, Prop("n", "val"), value), *extra))),))),))),))
    return Program(name, body).vprop("val").eprop("w")


def sssp_program(source: int = 0) -> Program:
    return _worklist("sssp", Bin("+", Prop("v", "val"), EProp("e", "w")), search=True).set("val", source, 0)


def wcc_program() -> Program:
    p = _worklist("wcc", Prop("v", "val"))
    return p.set("val", None, Ref("id"))


def bfs_program(root: int = 0) -> Program:
    return _worklist("bfs", Bin("+", Prop("v", "val"), Lit(1))).set("val", root, 0)


def pagerank_program() -> Program:
    share = Bin("/", Prop("v", "rank"), Call("out_degree", (Ref("v"),)))
    spread = ForVertices("v", Block((If(Bin(">", Call("out_degree", (Ref("v"),)), Lit(0)), Block((ForNeighbors("n", "v", Block((Reduce("sum", Prop("n", "acc"), share),))),))),)))
    scale = ForVertices("v", Block((Assign(Prop("v", "rank"), Bin("+", Lit(0.15), Bin("*", Lit(0.85), Prop("v", "acc")))),)))
    return Program("pagerank", Block((FixedPoint("r", Ref("changed"), Block((spread, scale))),))).vprop("rank", "double").vprop("acc", "double", 0)


def self_sum_program() -> Program:
    """A sum into the buffer that it reads."""
    return Program("self_sum", Block((ForVertices("v", Block((ForNeighbors("n", "v", Block((Reduce("sum", Prop("n", "val"), Prop("v", "val")),))),))),))).vprop("val")


def overwrite_program() -> Program:
    """A minimum and a plain write of the same buffer."""
    return _worklist("overwrite", Bin("+", Prop("v", "val"), EProp("e", "w")), search=True, extra=(Assign(Prop("n", "val"), Lit(0)),))


def two_reductions_program() -> Program:
    return _worklist("two_reductions", Bin("+", Prop("v", "val"), EProp("e", "w")), search=True, extra=(Reduce("min", Prop("n", "other"), Prop("v", "val")),)).vprop("other")


def accumulate_program(search: bool = False) -> Program:
    """``x(v) += y(v)`` for every neighbour."""
    edge = (Let("e", EdgeOf("v", "n")),) if search else ()
    return Program("accumulate", Block((ForVertices("v", Block((ForNeighbors("n", "v", Block((*edge, Assign(Prop("v", "x"), Bin("+", Prop("v", "x"), Prop("v", "y")))))),))),))).vprop("x").vprop("y")


def edge_min_program() -> Program:
    return Program("edge_min", Block((ForVertices("v", Block((ForNeighbors("n", "v", Block((Let("e", EdgeOf("v", "n")), Reduce("min", EProp("e", "y"), Prop("v", "x"))))),))),))).vprop("x").eprop("y")


def divergent_program() -> Program:
    """The edge search stands under a condition on the owner."""
    inner = ForNeighbors("n", "v", Block((Let("e", EdgeOf("v", "n")), Reduce("min", Prop("n", "val"), EProp("e", "w")))))
    return Program("divergent", Block((If(Ref("owner"), Block((ForVertices("v", Block((inner,))),)), by_owner=True),))).vprop("val").eprop("w")


def last_write_program() -> Program:
    """A reduction whose operator does not commute."""
    return _worklist("last_write", Bin("+", Prop("v", "val"), EProp("e", "w")), op="last", search=True)


LIBRARY = {p().name: p for p in (sssp_program, wcc_program, bfs_program, pagerank_program, self_sum_program, overwrite_program, two_reductions_program, accumulate_program, edge_min_program, divergent_program, last_write_program)}
