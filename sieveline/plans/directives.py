"""The thirteen rewrite directives: each names what it matches and the sub-plans it makes.

Configurations that an agent would write (sub-tasks, relevance rules, summaries, projections)
come from a :class:`Hints` record, filled by rules over task metadata or by the caller.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.text import token_count, tokens
from ..model import Task
from ..operators import Peripheral, Side
from .ir import EquijoinOp, FilterOp, GatherOp, MapOp, Op, ParallelMapOp, ProjectOp, ReduceOp, ResolveOp, SplitOp, UnnestOp


@dataclass(frozen=True)
class Hints:
    #: Chunk sizes and context shapes; where none are given, a generator fills them in.
    chunk_tokens: tuple[int, ...] = ()
    peripherals: tuple[Peripheral, ...] = ()
    columns: tuple[str, ...] = ("doc_id",)
    doc_key: str = "doc_id"
    parts: tuple[Task, ...] = ()
    chain: tuple[Op, ...] = ()
    metadata: Task | None = None
    summary: Task | None = None
    headers: Task | None = None
    relevant: Task | None = None
    finer_keys: tuple[str, ...] = ()
    partial: Callable[[Column], Column] | None = None
    final: Callable[[Column], Column] | None = None
    projection: Task | None = None
    compare: Callable[[Column, Column], Column] = lambda x, y: F.lit(True)
    resolve_keys: tuple[str, ...] = ()
    satisfied: Callable[[Column, Column], Column] = lambda text, answer: F.size(answer) > 0
    gleaning: int = 1
    #: How a reduce is refined: from the whole group and the answer so far.
    refine: Callable[[Column, Column], Column] | None = None


def union_items(name: str) -> Callable[[Column], Column]:
    """Sorted distinct items of all rows of a group."""

    def union(rows: Column) -> Column:
        # array_distinct compares each struct with all before it; of sorted ones the neighbours are enough.
        items = F.array_sort(F.flatten(F.transform(rows, lambda r: r[name])))
        new = lambda xs: F.filter(xs, lambda x, i: (i == 0) | ~x.eqNullSafe(F.get(xs, i - 1)))
        return F.get(F.transform(F.array(items), new), F.lit(0))

    return union


@dataclass(frozen=True)
class Directive:
    id: str
    name: str
    shape: tuple[type, ...]
    make: Callable[[tuple[Op, ...], Hints], list[tuple[Op, ...]]] = field(repr=False, default=None)

    def matches(self, ops: tuple[Op, ...]) -> bool:
        return len(ops) == len(self.shape) and all(isinstance(o, t) for o, t in zip(ops, self.shape))

    def apply(self, ops: tuple[Op, ...], hints: Hints) -> list[tuple[Op, ...]]:
        return self.make(ops, hints) if self.matches(ops) else []


def _fresh(op: Op) -> bool:
    return isinstance(op, MapOp) and not op.gleaning and not op.task.content.endswith(("_chunk", "_rendered"))


def _chunking(ops, h):
    (op,) = ops
    if not _fresh(op) or not op.task.is_list:
        return []
    text, out = op.task.content, []
    for n in h.chunk_tokens or (100,):
        for p in h.peripherals or (Peripheral(), Peripheral(previous=Side(tail=1))):
            # An item belongs to the chunk it starts in: context is shown, but the chunk is mapped.
            chunk = op.task.on(f"{text}_chunk")
            carry = tuple(c for c in h.columns if c != h.doc_key and c != text)
            out.append((SplitOp(text, n), GatherOp(f"{text}_chunk", p), MapOp(chunk), ReduceOp((h.doc_key,), (op.task.name,), union_items(op.task.name), op.task.name, ("split_chunk_num",), carry)))
    return out


def _metadata(ops, h):
    (op,) = ops
    return [(MapOp(h.metadata), op)] if h.metadata else []


def _lineage(ops, h):
    s, g = ops
    maps = tuple(t for t in (h.summary, h.headers) if t)
    if not maps:
        return []
    side = replace(g.peripheral.previous, middle=True, middle_key=h.summary.name) if h.summary else g.peripheral.previous
    return [(s, ParallelMapOp(maps), replace(g, peripheral=replace(g.peripheral, previous=side)))]


def _chunk_filter(ops, h):
    (op,) = ops
    return [(op, FilterOp(h.relevant))] if h.relevant else []


def _flatten(ops, h):
    g, m = ops
    return [(g, m, UnnestOp(m.task.name))] if m.task.is_list else []


def _levels(ops, h):
    (op,) = ops
    if not h.finer_keys or not h.partial:
        return []
    fine = replace(op, keys=(*op.keys, *h.finer_keys), summarise=h.partial, name="__partial", carry=())
    return [(fine, ReduceOp(op.keys, ("__partial",), h.final, op.name, h.finer_keys if op.order_by else ()))]


def _glean_map(ops, h):
    (op,) = ops
    return [(replace(op, gleaning=h.gleaning, satisfied=h.satisfied),)] if not op.gleaning else []


def _glean_reduce(ops, h):
    """The group stays at hand: where the validator objects, the answer is refined with the whole group, round by round."""
    (op,) = ops
    text = lambda rows: F.array_join(F.transform(rows, lambda r: F.to_json(r)), " ")
    # Without a rule of its own a refinement reads the group from its other end and unites.
    refine = h.refine or (lambda rows, answer: F.array_union(answer, op.summarise(F.reverse(rows))))

    def refined(rows):
        # One round an element, so that the answer so far is computed once a round.
        rounds = F.sequence(F.lit(1), F.lit(h.gleaning))
        return F.aggregate(rounds, op.summarise(rows), lambda acc, _: F.when(h.satisfied(text(rows), acc), acc).otherwise(refine(rows, acc)))

    return [(replace(op, summarise=refined),)]


def _resolve_keys(ops, h):
    (op,) = ops
    keys = [k for k in (h.resolve_keys or op.keys) if k in op.keys]
    return [(*[ResolveOp(k, h.compare) for k in keys], op)] if keys else []


def _chain(ops, h):
    (op,) = ops
    return [(*h.chain, op)] if h.chain else []


def _isolate(ops, h):
    (op,) = ops
    if len(h.parts) < 2 or not _fresh(op):
        return []
    names = [t.name for t in h.parts]
    merged = lambda: F.array_sort(F.array_distinct(F.concat(*[F.col(n) for n in names])))
    return [(ParallelMapOp(h.parts), ProjectOp(op.task.name, merged, (*names, *op.drop)))]


def _preaggregate(ops, h):
    (op,) = ops
    if not h.projection:
        return []
    drop = tuple(p for p in op.payload if p != h.projection.name)
    return [(MapOp(h.projection, drop), replace(op, payload=(h.projection.name,), summarise=h.final or op.summarise))]


def _prejoin(ops, h):
    (op,) = ops
    return [(MapOp(h.projection), op)] if h.projection else []


DIRECTIVES = (
    Directive("D1", "document chunking", (MapOp,), _chunking),
    Directive("D2", "document metadata", (SplitOp,), _metadata),
    Directive("D3", "header lineage and summaries", (SplitOp, GatherOp), _lineage),
    Directive("D4", "chunk filtering", (GatherOp,), _chunk_filter),
    Directive("D5", "flattening", (GatherOp, MapOp), _flatten),
    Directive("D6", "multi-level aggregation", (ReduceOp,), _levels),
    Directive("D7", "gleaning a map", (MapOp,), _glean_map),
    Directive("D8", "gleaning a reduce", (ReduceOp,), _glean_reduce),
    Directive("D9", "duplicate key resolution", (ReduceOp,), _resolve_keys),
    Directive("D10", "chaining", (MapOp,), _chain),
    Directive("D11", "isolating", (MapOp,), _isolate),
    Directive("D12", "pre-aggregation", (ReduceOp,), _preaggregate),
    Directive("D13", "pre-joining", (EquijoinOp,), _prejoin),
)
BY_ID = {d.id: d for d in DIRECTIVES}


def first_tokens(col: str, n: int, name: str = "front") -> Task:
    """A metadata task over the front matter only."""
    from pyspark.sql import types as T

    return Task(name, col, lambda c: F.concat_ws(" ", F.slice(tokens(c), 1, n)), T.StringType())


def chunk_sizes(limit: int, mean_tokens: float, cap: int | None = None) -> list[int]:
    """Five sizes from 15 % to 75 % of the model's limit and six from 15 % to 100 % of the mean length."""
    sizes = [limit * (15 + 15 * i) // 100 for i in range(5)] + [int(mean_tokens * (15 + 17 * i) / 100) for i in range(6)]
    sizes = sorted({max(1, s) for s in sizes if s <= limit})
    if cap and len(sizes) > cap:
        sizes = [sizes[round(i * (len(sizes) - 1) / (cap - 1))] for i in range(cap)]
    return sizes


def gather_shapes(doc_tokens: float, chunk_tokens: float, summary: str | None = None) -> list[Peripheral]:
    """Context candidates: three always, more as the chunk gets small against the document."""
    out = [Peripheral(), Peripheral(Side(tail=1)), Peripheral(Side(tail=1), Side(head=1))]
    ratio = doc_tokens / max(chunk_tokens, 1)
    if ratio > 1.5:
        root = int(ratio**0.5)
        if root > 1:
            out.append(Peripheral(Side(tail=root)))
        if ratio > 10:
            out.append(Peripheral(Side(tail=5), Side(head=2)))
        if ratio > 5 and summary:
            out.append(Peripheral(Side(tail=1, middle=True, middle_key=summary)))
    return out


def fold_batches(limit: int, mean_tokens: float) -> list[int]:
    """Batches that fill 20, 40, 60, 75 and 90 % of the context window."""
    return [max(1, int(limit * p / 100 / max(mean_tokens, 1))) for p in (20, 40, 60, 75, 90)]


def partition_asks(task: Task, parts: list[Task], size: int = 3) -> list[list[Task]]:
    """Groups of at most ``size`` related sub-tasks, in order."""
    return [parts[i : i + size] for i in range(0, len(parts), size)]


def mean_tokens(df, col: str) -> float:
    return df.agg(F.avg(token_count(F.col(col)))).first()[0] or 0.0
