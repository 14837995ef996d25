"""Binary operators, monoids and semirings as Catalyst expressions: code generation specializes each use."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class BinaryOp:
    name: str
    apply: Callable[[Column, Column], Column]
    result: str | None = None  # a Spark type, where it is not that of the inputs
    uses_left: bool = True
    uses_right: bool = True

    def __call__(self, a: Column, b: Column) -> Column:
        return self.apply(a, b)


def _flag(c: Column) -> Column:
    return c.cast("double") != 0 if c is not None else c


def _logical(f):
    return lambda a, b: f(a.cast("boolean"), b.cast("boolean"))


BINARY: dict[str, BinaryOp] = {
    o.name: o
    for o in (
        BinaryOp("first", lambda a, b: a, uses_right=False),
        BinaryOp("second", lambda a, b: b, uses_left=False),
        BinaryOp("pair", lambda a, b: F.lit(1).cast("long"), "long", False, False),
        BinaryOp("any", lambda a, b: F.coalesce(a, b)),
        BinaryOp("min", lambda a, b: F.least(a, b)),
        BinaryOp("max", lambda a, b: F.greatest(a, b)),
        BinaryOp("plus", lambda a, b: a + b),
        BinaryOp("minus", lambda a, b: a - b),
        BinaryOp("rminus", lambda a, b: b - a),
        BinaryOp("times", lambda a, b: a * b),
        BinaryOp("div", lambda a, b: F.try_divide(a, b), "double"),
        BinaryOp("rdiv", lambda a, b: F.try_divide(b, a), "double"),
        BinaryOp("eq", lambda a, b: a == b, "boolean"),
        BinaryOp("ne", lambda a, b: a != b, "boolean"),
        BinaryOp("gt", lambda a, b: a > b, "boolean"),
        BinaryOp("lt", lambda a, b: a < b, "boolean"),
        BinaryOp("ge", lambda a, b: a >= b, "boolean"),
        BinaryOp("le", lambda a, b: a <= b, "boolean"),
        BinaryOp("lor", _logical(lambda a, b: a | b), "boolean"),
        BinaryOp("land", _logical(lambda a, b: a & b), "boolean"),
        BinaryOp("lxor", _logical(lambda a, b: a != b), "boolean"),
        BinaryOp("lxnor", _logical(lambda a, b: a == b), "boolean"),
    )
}


class DomainMismatch(TypeError):
    pass


#: Domains of values and the Spark types that hold them; unsigned ones have the next wider type and a lower bound of 0.
DOMAINS: dict[str, str] = {
    "bool": "boolean",
    "int8": "tinyint",
    "int16": "smallint",
    "int32": "int",
    "int64": "bigint",
    "uint8": "smallint",
    "uint16": "int",
    "uint32": "bigint",
    "uint64": "decimal(20,0)",
    "fp32": "float",
    "fp64": "double",
}
ARITHMETIC = ("plus", "minus", "rminus", "times", "div", "rdiv")


def into(c: Column, domain: str) -> Column:
    """A value in a domain; what does not fit (a sum that is too large, a negative value in an unsigned domain) is null,
    and so no entry."""
    if domain not in DOMAINS:
        raise DomainMismatch(f"no domain {domain}")
    got = c.try_cast(DOMAINS[domain])
    if not domain.startswith("uint"):
        return got
    most = F.lit(str((1 << int(domain[4:])) - 1)).cast("decimal(20,0)")
    return F.when((got >= 0) & (got <= most), got)


def typed(op: BinaryOp, domain: str) -> BinaryOp:
    """An operator whose operands and result are of one domain (results of comparisons and logical ones are Boolean).
    Integers meet in a type wide enough for any result, but for division, which is real until it is cast back."""
    if domain not in DOMAINS:
        raise DomainMismatch(f"no domain {domain}")
    if domain == "bool" and op.name in ARITHMETIC:
        raise DomainMismatch(f"{op.name} of Boolean values")
    wide = {"int64": "decimal(19,0)", "uint64": "decimal(20,0)", "uint32": "decimal(10,0)"}.get(domain, "bigint" if "int" in domain else None)

    def run(a: Column, b: Column) -> Column:
        a, b = into(a, domain), into(b, domain)
        if wide is not None and op.name in ARITHMETIC:
            kind = "double" if op.name in ("div", "rdiv") else wide
            a, b = a.cast(kind), b.cast(kind)
        made = op.apply(a, b)
        return made if op.result == "boolean" else made.cast("bigint") if op.result == "long" else into(made, domain)

    return BinaryOp(f"{op.name}_{domain}", run, op.result, op.uses_left, op.uses_right)


@dataclass(frozen=True)
class Monoid:
    """An associative operator with its identity: as an aggregate, and between two columns."""

    name: str
    aggregate: Callable[[Column], Column]
    combine: Callable[[Column, Column], Column]
    identity: object = None

    def total(self, c: Column) -> Column:
        """The aggregate, with the identity for no rows."""
        got = self.aggregate(c)
        return got if self.identity is None else F.coalesce(got, F.lit(self.identity))


_INF = float("inf")
MONOIDS: dict[str, Monoid] = {
    m.name: m
    for m in (
        Monoid("plus", F.sum, lambda a, b: a + b, 0),
        Monoid("times", F.product, lambda a, b: a * b, 1),
        Monoid("min", F.min, F.least, _INF),
        Monoid("max", F.max, F.greatest, -_INF),
        Monoid("lor", lambda c: F.bool_or(c.cast("boolean")), BINARY["lor"].apply, False),
        Monoid("land", lambda c: F.bool_and(c.cast("boolean")), BINARY["land"].apply, True),
        Monoid("lxor", lambda c: F.sum(c.cast("boolean").cast("int")) % 2 == 1, BINARY["lxor"].apply, False),
        Monoid("eq", lambda c: F.sum((~c.cast("boolean")).cast("int")) % 2 == 0, BINARY["lxnor"].apply, True),
    )
}


@dataclass(frozen=True)
class Semiring:
    name: str
    add: Monoid
    mul: BinaryOp

    @classmethod
    def define(cls, name: str, add: Monoid, mul: BinaryOp) -> Semiring:
        """A semiring of the user's own: any monoid over any product, domains as the expressions give."""
        return cls(name, add, mul)


SEMIRINGS: dict[str, Semiring] = {
    s.name: s
    for s in (
        Semiring("plus_times", MONOIDS["plus"], BINARY["times"]),
        Semiring("or_and", MONOIDS["lor"], BINARY["land"]),
        Semiring("min_plus", MONOIDS["min"], BINARY["plus"]),
        Semiring("max_plus", MONOIDS["max"], BINARY["plus"]),
        Semiring("min_times", MONOIDS["min"], BINARY["times"]),
        Semiring("min_second", MONOIDS["min"], BINARY["second"]),
        Semiring("min_first", MONOIDS["min"], BINARY["first"]),
        Semiring("plus_pair", MONOIDS["plus"], BINARY["pair"]),
        Semiring("plus_second", MONOIDS["plus"], BINARY["second"]),
        Semiring("plus_first", MONOIDS["plus"], BINARY["first"]),
    )
}
