"""Back ends: the same plan as SQL rows (S), dense blocks over Arrow (B), vertex programs that push (V), or mixed (hybrid)."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import chain, ops, reorder, storage
from ..operators.superstep import apply, gather, gather_apply, iterate
from ..sources.shared import reliable
from ..types import GraphMatrix, Strategy, VertexState
from . import ir


class Backend:
    """Rows: joins and aggregates. Other back ends replace single steps."""

    name = "S"

    def __init__(self, strategy: Strategy):
        self.strategy = strategy

    def emit(self, node: ir.PlanNode) -> GraphMatrix | VertexState:
        return getattr(self, "on_" + type(node).__name__.lower())(node)

    def on_load(self, n):
        return n.graph

    def on_state(self, n):
        return n.state

    def on_transpose(self, n):
        return self.emit(n.child).T

    def on_scale(self, n):
        return ops.scaled(self.emit(n.child), n.factor)

    def on_expand(self, n):
        return {"sym": storage.mirror, "herm": storage.mirror_hermitian, "unit": storage.with_unit_diagonal}[n.kind](self.emit(n.child))

    def on_sum(self, n):
        return self.emit(n.child).summed()

    def on_reorder(self, n):
        gm = self.emit(n.child)
        return reorder.relabel(gm, reorder.relabelling(gm, n.method))

    def on_combine(self, n):
        gm, x = self.emit(n.child.matrix), self.emit(n.child.state)
        fold = {"sum": F.sum, "min": F.min, "max": F.max}[n.fold]
        return self.superstep(gm, x, fold)

    def on_finalize(self, n):
        return self.emit(n.child)

    def on_mergeedges(self, n):
        return ops.add_all([self.emit(p) for p in n.parts])

    def on_contract(self, n):
        return chain.product([self.emit(p) for p in n.parts], n.mode)

    def on_iterate(self, n):
        gm = self.emit(n.matrix)
        return iterate(lambda s: self.superstep(gm, s, F.sum), self.emit(n.state), n.times)

    def superstep(self, gm, x, fold):
        if self.strategy.reorder == "none":
            return gather_apply(gm, x, combine=fold, strategy=self.strategy)
        perm = reliable(reorder.relabelling(gm, self.strategy.reorder))
        new = gather_apply(reorder.relabel(gm, perm), reorder.relabel_state(x, perm), combine=fold, strategy=self.strategy)
        return VertexState(reorder.restore(new, perm).df, gm.meta.n_rows)


class BlockBackend(Backend):
    """Dense blocks in NumPy: a vector is a matrix of one column."""

    name = "B"

    def superstep(self, gm, x, fold):
        column = GraphMatrix(x.df.select(F.col("id").alias("dst"), F.lit(0).cast("bigint").alias("src"), F.col("s").alias("w")), gm.meta)
        out = ops.mm_blocks(gm, column, self.strategy.bucket or 256)
        return VertexState(out.edges.select(F.col("dst").alias("id"), F.col("w").alias("s")), gm.meta.n_rows)

    def on_contract(self, n):
        parts = [self.emit(p) for p in n.parts]
        out = parts[0]
        for p in parts[1:]:
            out = ops.mm_panel(out, p) if ops.fits(out) else ops.mm_blocks(out, p, self.strategy.bucket or 256)
        return out


class VertexBackend(Backend):
    """Push form: every active vertex computes along its out-edges and scatters; receivers accumulate."""

    name = "V"

    def superstep(self, gm, x, fold):
        active = VertexState(x.df.where("s <> 0") if fold is F.sum else x.df, x.n)
        sent = gather(gm, active, strategy=Strategy(direction="push"))
        return VertexState(apply(sent, fold), gm.meta.n_rows)


class HybridBackend(Backend):
    name = "hybrid"

    def on_contract(self, n):
        parts = [self.emit(p) for p in n.parts]
        out = parts[0]
        for p in parts[1:]:
            out = ops.mm_hybrid(out, p, self.strategy.bucket or 64)
        return out


BACKENDS = {b.name: b for b in (Backend, BlockBackend, VertexBackend, HybridBackend)}


def emit(node: ir.PlanNode, strategy: Strategy = Strategy()) -> GraphMatrix | VertexState:
    return BACKENDS[strategy.backend](strategy).emit(node)
