"""Deferred calls: operations build a graph, which is rewritten with what semirings and masks allow before it runs.

Catalyst sees joins and aggregates only; that a mask may go below a sum of products, or that a product ignores its
values, is known here. wait() lowers the graph to the eager operators and settles the result.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.algebra import BINARY, Monoid, Semiring
from ..operators import multiply, pieces
from ..operators.objects import Descriptor, GraphVector, SparseMatrix
from .loop import settle


@dataclass(frozen=True, eq=False)
class Lazy:
    """One deferred call; its inputs are deferred calls too."""

    op: str
    inputs: tuple[Lazy, ...] = ()
    args: dict = field(default_factory=dict)

    @property
    def T(self) -> Lazy:
        return Lazy("transpose", (self,))

    def mxv(self, x: Lazy, semiring: Semiring) -> Lazy:
        return Lazy("mxv", (self, x), {"semiring": semiring})

    def vxm(self, a: Lazy, semiring: Semiring) -> Lazy:
        return Lazy("vxm", (self, a), {"semiring": semiring})

    def mxm(self, b: Lazy, semiring: Semiring) -> Lazy:
        return Lazy("mxm", (self, b), {"semiring": semiring})

    def mask(self, m: Lazy, complement: bool = False, structural: bool = False) -> Lazy:
        return Lazy("mask", (self, m), {"complement": complement, "structural": structural})

    def apply(self, f: Callable) -> Lazy:
        return Lazy("apply", (self,), {"f": f})

    def scale(self, factor) -> Lazy:
        """Every value times a constant."""
        return Lazy("scale", (self,), {"factor": factor})

    def accumulate(self, old: Lazy, monoid: Monoid) -> Lazy:
        return Lazy("accumulate", (self, old), {"monoid": monoid})

    def reduce_rows(self, monoid: Monoid) -> Lazy:
        return Lazy("reduce_rows", (self,), {"monoid": monoid})

    def reduce(self, monoid: Monoid) -> Lazy:
        return Lazy("reduce", (self,), {"monoid": monoid})

    def plan(self) -> tuple[Lazy, list[str]]:
        """The rewritten graph and the names of the rules that changed it, in order."""
        used: list[str] = []
        return _rewritten(self, used, {}), used

    def shape(self) -> str:
        """The graph in one line."""
        return self.op if not self.inputs else f"{self.op}({', '.join(x.shape() for x in self.inputs)})"

    def wait(self, optimize: bool = True) -> DataFrame:
        """Runs the graph: the stored entries, or one row (v) of a reduction."""
        node = self.plan()[0] if optimize else self
        made = _lowered(node, {})
        return settle(made if isinstance(made, DataFrame) else made.df)[0]


def stored(a: SparseMatrix | GraphVector, ones: bool = False) -> Lazy:
    """A leaf. ones: all stored values are 1, so that products with them need not read them."""
    return Lazy("stored", (), {"of": a, "ones": ones})


def _ones(node: Lazy) -> bool:
    return node.op == "stored" and node.args["ones"] or node.op == "transpose" and _ones(node.inputs[0])


def _double_transpose(n: Lazy):
    if n.op == "transpose" and n.inputs[0].op == "transpose":
        return n.inputs[0].inputs[0]


def _transpose_of_product(n: Lazy):
    if n.op == "transpose" and n.inputs[0].op == "mxm" and "mask" not in n.inputs[0].args:
        a, b = n.inputs[0].inputs
        return Lazy("mxm", (b.T, a.T), {"semiring": multiply.flipped(n.inputs[0].args["semiring"])})


def _row_vector(n: Lazy):
    if n.op == "vxm":
        x, a = n.inputs
        return Lazy("mxv", (a.T, x), {"semiring": multiply.flipped(n.args["semiring"])})


def _mask_first(n: Lazy):
    if n.op == "mask" and n.inputs[0].op in ("mxv", "mxm") and "mask" not in n.inputs[0].args:
        made, m = n.inputs
        return replace(made, args=made.args | {"mask": m, "complement": n.args["complement"], "structural": n.args["structural"]})


def _mask_below_map(n: Lazy):
    if n.op == "mask" and n.inputs[0].op in ("apply", "scale"):
        inner = n.inputs[0]
        return replace(inner, inputs=(replace(n, inputs=(inner.inputs[0], n.inputs[1])),))


def _structure_only(n: Lazy):
    if n.op not in ("mxv", "mxm") or n.args["semiring"].mul.name != "times":
        return None
    left, right = _ones(n.inputs[0]), _ones(n.inputs[1])
    if left or right:
        name = "pair" if left and right else "second" if left else "first"
        ring = n.args["semiring"]
        return replace(n, args=n.args | {"semiring": Semiring(f"{ring.add.name}_{name}", ring.add, BINARY[name])})


def _maps_joined(n: Lazy):
    if n.op == "apply" and n.inputs[0].op == "apply":
        f, g = n.args["f"], n.inputs[0].args["f"]
        return Lazy("apply", n.inputs[0].inputs, {"f": lambda c: f(g(c))})
    if n.op == "scale" and n.inputs[0].op == "scale":
        return Lazy("scale", n.inputs[0].inputs, {"factor": n.args["factor"] * n.inputs[0].args["factor"]})


def _constant_after_sum(n: Lazy):
    if n.op in ("reduce", "reduce_rows") and n.inputs[0].op == "scale" and n.args["monoid"].name == "plus":
        inner = n.inputs[0]
        return replace(n, inputs=inner.inputs).scale(inner.args["factor"])
    if n.op in ("mxv", "mxm", "product_total") and n.args["semiring"].name == "plus_times":
        for at, x in enumerate(n.inputs):
            if x.op == "scale":
                inputs = tuple(x.inputs[0] if k == at else y for k, y in enumerate(n.inputs))
                return replace(n, inputs=inputs).scale(x.args["factor"])


def _reduce_fused(n: Lazy):
    if n.op == "reduce" and n.inputs[0].op == "reduce_rows" and n.inputs[0].args["monoid"].name == n.args["monoid"].name:
        return replace(n, inputs=n.inputs[0].inputs)
    if n.op == "reduce" and n.inputs[0].op == "mxm" and n.inputs[0].args["semiring"].add.name == n.args["monoid"].name:
        return Lazy("product_total", n.inputs[0].inputs, n.inputs[0].args)


def _some_only(n: Lazy):
    """or-and over values that are all true: a row needs one match, not all."""
    if n.op == "mxv" and n.args["semiring"].name == "or_and" and all(map(_ones, n.inputs)):
        return Lazy("any_match", n.inputs, n.args)


#: Name and rule; a rule gives a new node, or None where it does not apply.
RULES: tuple[tuple[str, Callable], ...] = (
    ("row vector times matrix", _row_vector),
    ("double transpose", _double_transpose),
    ("transpose of product", _transpose_of_product),
    ("mask below map", _mask_below_map),
    ("mask first", _mask_first),
    ("maps joined", _maps_joined),
    ("constant after sum", _constant_after_sum),
    ("early exit", _some_only),
    ("structure only", _structure_only),
    ("reduce fused", _reduce_fused),
)


def _rewritten(node: Lazy, used: list[str], done: dict[int, tuple[Lazy, Lazy]]) -> Lazy:
    """Rules to a fixed point, top down and again after the inputs changed; shared nodes stay shared. Every rule removes
    a node, moves one towards the leaves or the root for good, or drops a read, so this ends."""
    if id(node) in done:
        return done[id(node)][1]
    first = node
    while True:
        for name, rule in RULES:
            got = rule(node)
            if got is not None:
                used.append(name)
                node = got
                break
        else:
            inputs = tuple(_rewritten(x, used, done) for x in node.inputs)
            args = {k: _rewritten(v, used, done) if isinstance(v, Lazy) else v for k, v in node.args.items()}
            if all(x is y for x, y in zip(inputs, node.inputs)) and all(args[k] is node.args[k] for k in args):
                # The node itself is kept with its result, so that its id stays taken.
                done[id(first)] = (first, node)
                return node
            node = replace(node, inputs=inputs, args=args)


def _lowered(node: Lazy, done: dict[int, object]):
    """Eager objects of a graph; a node that several calls share is lowered once."""
    if id(node) not in done:
        done[id(node)] = _one(node, [_lowered(x, done) for x in node.inputs], {k: _lowered(v, done) if isinstance(v, Lazy) else v for k, v in node.args.items()})
    return done[id(node)]


def _one(node: Lazy, x: list, args: dict):
    desc = Descriptor(mask_complement=args.get("complement", False), mask_structural=args.get("structural", False))
    match node.op:
        case "stored":
            return args["of"]
        case "transpose":
            return x[0].T
        case "mxv":
            return multiply.mxv(x[0], x[1], args["semiring"], args.get("mask"), desc)
        case "vxm":
            return multiply.vxm(x[0], x[1], args["semiring"])
        case "any_match":
            rows = multiply._masked(x[0].df.select("i", "j"), args.get("mask"), desc)
            met = rows.join(x[1].df.select(F.col("i").alias("j")), "j", "left_semi").select("i").distinct()
            return GraphVector(met.withColumn("v", F.lit(True)), x[0].nrows)
        case "mxm":
            return multiply.mxm(x[0], x[1], args["semiring"], args.get("mask"), desc=desc)
        case "product_total":
            ring, mask = args["semiring"], args.get("mask")
            if ring.add.name == "plus" and ring.mul.name == "pair" and mask is not None and not desc.mask_complement:
                # Products that are all 1 are counted where they are made.
                return multiply.mxm(x[0], x[1], ring, mask, desc=desc).df.agg(ring.add.total(F.col("v")).alias("v"))
            made = multiply.products(x[0], x[1], args["semiring"], args.get("mask"), desc)
            return made.agg(args["semiring"].add.total(F.col("p")).alias("v"))
        case "mask":
            keys = ["i"] if isinstance(x[0], GraphVector) else ["i", "j"]
            return pieces._like(x[0], x[0].df.join(x[1].selected(args["structural"]), keys, "left_anti" if args["complement"] else "left_semi"))
        case "apply" | "scale":
            f = args["f"] if node.op == "apply" else lambda c: c * F.lit(args["factor"])
            return x[0].withColumn("v", f(F.col("v"))) if isinstance(x[0], DataFrame) else pieces.apply(x[0], f)
        case "accumulate":
            return pieces.ewise_add(x[0], x[1], args["monoid"])
        case "reduce_rows":
            return pieces.reduce_rows(x[0], args["monoid"])
        case "reduce":
            return pieces.reduce_scalar(x[0], args["monoid"])
    raise ValueError(f"no operation {node.op}")
