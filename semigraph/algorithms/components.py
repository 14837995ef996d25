"""Connected components: (i, v) with the smallest vertex of each component, by several schemes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.loop import Trace, settle, written
from .traversal import bfs
from ..operators.objects import SparseMatrix


def _vertices(edges: DataFrame) -> DataFrame:
    return edges.select("i").union(edges.select("j")).distinct()


def hook_shortcut(edges: DataFrame, sparsified: bool = False, full_jump: bool = False, trace: Trace | None = None, max_rounds: int = 1000) -> DataFrame:
    """Rounds of: smallest grandparent among neighbours, hooked onto the parent and the vertex itself,
    then a jump to the grandparent; ends when no grandparent changes. sparsified: only changed
    grandparents are sent. full_jump: jumps until trees are stars (alternating and unconditional hooking: star_hooking)."""
    state, _ = settle(_vertices(edges).select("i", F.col("i").alias("p"), F.col("i").alias("g"), F.lit(True).alias("fresh")))
    for _ in range(max_rounds):
        sent = state.filter("fresh") if sparsified else state
        q = edges.select("i", "j").join(sent.select(F.col("i").alias("j"), F.col("g").alias("x")), "j").groupBy("i").agg(F.min("x").alias("q"))
        with_q = state.join(q, "i", "left").withColumn("q", F.coalesce("q", "g"))
        hooked = with_q.groupBy(F.col("p").alias("i")).agg(F.min("q").alias("h"))
        low = with_q.join(hooked, "i", "left").select("i", F.least("p", "q", "g", F.coalesce("h", "p")).alias("p"), F.col("g").alias("old"))
        low, _ = settle(low)
        while True:
            up = low.select(F.col("i").alias("p"), F.col("p").alias("g"))
            jumped, got = settle(low.join(up, "p").select("i", "p", "g", "old"), moved=(F.col("g") < F.col("p")).cast("int"))
            if not full_jump or not got["moved"]:
                break
            low = jumped.select("i", F.col("g").alias("p"), "old")
        state, got = settle(jumped.select("i", F.least("p", "g").alias("p") if full_jump else "p", "g", (F.col("g") != F.col("old")).alias("fresh")), moved=F.col("fresh").cast("int"))
        if trace is not None:
            trace.add("pull", int(got["n"]), int(got["moved"]))
        if not got["moved"]:
            return state.select("i", F.col("g").alias("v"))
    raise RuntimeError("no fixed point")


def _stars(forest: DataFrame) -> DataFrame:
    """(i, p, star): whether a vertex's tree is a star, of parents (i, p). A vertex whose grandparent differs from its
    parent spoils its own tree's star, its grandparent's and its parent's."""
    up = forest.select(F.col("i").alias("p"), F.col("p").alias("g"))
    two = forest.join(up, "p").select("i", "p", "g")
    deep = two.filter("p <> g").select(F.explode(F.array("i", "g")).alias("i")).distinct().withColumn("deep", F.lit(True))
    own = two.join(deep, "i", "left").select("i", "p", F.coalesce("deep", F.lit(False)).alias("deep"))
    # A vertex takes over what its parent, the root or one below it, has found.
    above = own.select(F.col("i").alias("p"), F.col("deep").alias("above"))
    return own.join(above, "p").select("i", "p", (~F.col("deep") & ~F.col("above")).alias("star"))


def _hook(forest: DataFrame, edges: DataFrame, choose, when) -> DataFrame:
    """Parents after the roots of stars have hooked onto a neighbouring tree's parent, where when allows it."""
    stars = written(_stars(forest))
    far = stars.select(F.col("i").alias("j"), F.col("p").alias("q"))
    near = edges.select("i", "j").join(stars.filter("star").select("i", "p"), "i").join(far, "j")
    target = near.filter(when(F.col("q"), F.col("p"))).groupBy(F.col("p").alias("i")).agg(choose("q").alias("to"))
    made, got = settle(forest.join(target, "i", "left").select("i", F.coalesce("to", "p").alias("p"), F.col("to").isNotNull().cast("int").alias("hooked")), hooked=F.col("hooked"))
    return made, got["hooked"]


def star_hooking(edges: DataFrame, alternate: bool = False, trace: Trace | None = None, max_rounds: int = 1000) -> DataFrame:
    """Rounds of three steps. Stars whose vertices have a neighbour under a smaller parent hook onto the smallest;
    stars that are still there hook unconditionally onto any neighbouring tree, so that each round at least halves
    the stars that are not whole components; then every vertex jumps to its grandparent. alternate: instead of the
    unconditional step, rounds hook onto smaller and onto larger parents in turn, and jump until trees are stars."""
    forest, _ = settle(_vertices(edges).select("i", F.col("i").alias("p")))
    idle = 0
    for turn in range(max_rounds):
        upward = alternate and turn % 2 == 1
        smaller, larger = (lambda q, p: q < p), (lambda q, p: q > p)
        low, hooked = _hook(forest, edges, F.max if upward else F.min, larger if upward else smaller)
        if not alternate:
            # What hooked just now hangs below another tree, so a star that is left has no smaller neighbour.
            low, more = _hook(low.select("i", "p"), edges, F.min, lambda q, p: q != p)
            hooked += more
        moved = 0
        while True:
            up = low.select(F.col("i").alias("p"), F.col("p").alias("g"))
            low, got = settle(low.select("i", "p").join(up, "p").select("i", F.col("g").alias("p"), (F.col("g") != F.col("p")).cast("int").alias("moved")), moved=F.col("moved"))
            moved += got["moved"]
            if not alternate or not got["moved"]:
                break
        forest = low.select("i", "p")
        if trace is not None:
            trace.add("pull", hooked, moved)
        # Alternating rounds end when neither direction hooks.
        idle = idle + 1 if not hooked and not moved else 0
        if idle > (1 if alternate else 0):
            least = forest.groupBy("p").agg(F.min("i").alias("v"))
            return forest.join(least, "p").select("i", "v")
    raise RuntimeError("no fixed point")


def edge_filter(edges: DataFrame) -> DataFrame:
    """Edges hook their larger end's root onto the smaller; trees are flattened; edges inside one tree go."""
    label, _ = settle(_vertices(edges).select("i", F.col("i").alias("v")))
    left, got = settle(edges.filter("i <> j").select(F.col("i").alias("a"), F.col("j").alias("b")))
    while got["n"]:
        hook = left.select(F.greatest("a", "b").alias("r"), F.least("a", "b").alias("to")).groupBy("r").agg(F.min("to").alias("to"))
        tree, _ = settle(left.select(F.col("a").alias("r")).union(left.select("b")).distinct().join(hook, "r", "left").select("r", F.coalesce("to", "r").alias("to")))
        while True:
            up = tree.select(F.col("r").alias("to"), F.col("to").alias("top"))
            tree, moved = settle(tree.join(up, "to").select("r", F.col("top").alias("to"), (F.col("top") < F.col("to")).alias("moved")), moved=F.col("moved").cast("int"))
            tree = tree.select("r", "to")
            if not moved["moved"]:
                break
        label, _ = settle(label.join(tree.select(F.col("r").alias("v"), F.col("to").alias("top")), "v", "left").select("i", F.coalesce("top", "v").alias("v")))
        of = lambda end, new: tree.select(F.col("r").alias(end), F.col("to").alias(new))
        left, got = settle(left.join(of("a", "x"), "a").join(of("b", "y"), "b").filter("x <> y").select(F.col("x").alias("a"), F.col("y").alias("b")).distinct())
    return label


def label_propagation(edges: DataFrame, label: DataFrame | None = None) -> DataFrame:
    """The smallest label among neighbours, again and again; only changed labels are sent."""
    label = label if label is not None else _vertices(edges).select("i", F.col("i").alias("v"))
    state, got = settle(label.withColumn("fresh", F.lit(True)))
    while got["n"]:
        new = edges.select("i", "j").join(state.filter("fresh").select(F.col("i").alias("j"), F.col("v").alias("x")), "j").groupBy("i").agg(F.min("x").alias("x"))
        less = F.coalesce(F.col("x") < F.col("v"), F.lit(False))
        state, moved = settle(state.join(new, "i", "left").select("i", F.least("v", "x").alias("v"), less.alias("fresh")), moved=F.col("fresh").cast("int"))
        if not moved["moved"]:
            break
    return state.select("i", "v")


def multistep(edges: DataFrame) -> DataFrame:
    """The component of the vertex of highest degree by traversal, the rest by propagation."""
    top = edges.groupBy("i").count().orderBy(F.desc("count"), "i").first()
    if top is None:
        return _vertices(edges).select("i", F.col("i").alias("v"))
    found, _ = settle(bfs(SparseMatrix(edges.select("i", "j", F.lit(1).alias("v"))), top["i"]).select("i"))
    low = found.agg(F.min("i").alias("v"))
    big = found.crossJoin(F.broadcast(low))
    rest = edges.join(found, "i", "left_anti")
    return big.unionByName(label_propagation(rest))


def sizes(labels: DataFrame) -> DataFrame:
    return labels.groupBy("v").agg(F.count(F.lit(1)).alias("n"))


VARIANTS = {
    "hook_shortcut": hook_shortcut,
    "sparsified": lambda e: hook_shortcut(e, sparsified=True),
    "full_jump": lambda e: hook_shortcut(e, full_jump=True),
    "alternating": lambda e: star_hooking(e, alternate=True),
    "unconditional": lambda e: star_hooking(e),
    "edge_filter": edge_filter,
    "label_propagation": label_propagation,
    "multistep": multistep,
}
