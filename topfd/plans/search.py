"""The pruned search for the k dependencies of largest redundancy, its variants, and exhaustive discovery by the same kernel.

Control stays on the driver: numbers of classes, a few hundred bitmasks, k answers. Each round collects up to `batch` candidates in bound order, then one Spark
job checks them all and one more fetches a refuting pair of rows for each that failed. Every difference set found is shared by all right-hand sides.

Variants: `core` goes through right-hand sides one by one in schema order, with bounds of single attributes; `ordered` adds the ascending order;
`ordered_pairs` adds bounds of pairs; `full` adds the scheduler that always takes the most promising tree. Any answer is the same.
"""

from __future__ import annotations

import heapq
import time
from collections.abc import Iterable
from dataclasses import dataclass, field
from functools import partial

from pyspark.sql import DataFrame

from ..model import FD, FD_SCHEMA, STATS_SCHEMA, TRACE_SCHEMA, Limits, Relation, mask_of
from ..operators import cardinality, evidence
from ..operators.held import Held, hold
from .bounds import PairMatrix, attribute_order
from .cost import Meter
from .progress import Progress
from .spread import spread_candidates
from .transversal import Antichain, Counters, Tree

VARIANTS = {
    "core": {"order": "schema", "bound": "single", "scheduler": "sequential"},
    "ordered": {"order": "ascending", "bound": "single", "scheduler": "sequential"},
    "ordered_pairs": {"order": "ascending", "bound": "pairs", "scheduler": "sequential"},
    "full": {"order": "ascending", "bound": "pairs", "scheduler": "global"},
}
#: Candidates of a round; more where k asks for more answers.
BATCH, MOST_BATCH = 24, 192
#: Rows of a slice, about, and the smallest slice's share: relations of fewer than four slices are checked whole at once. Where the driver's sample holds
#: slices of that size, they are not asked for again.
SLICE_ROWS, MOST_SLICES = 25_000, 64
#: Candidates that the antichains of a run may hold together; beyond, the trees go on, which hold a stack alone.
MOST_SETS = 30_000


class TopK:
    """The k best so far in canonical order; tau is the redundancy that a candidate has to reach."""

    def __init__(self, rel: Relation, k: int | None, ties: str = "canonical"):
        if k is not None and k < 1:
            raise ValueError("k is 1 or more")
        if ties not in ("canonical", "any"):
            raise ValueError("ties is 'canonical' or 'any'")
        self.rel, self.k, self.any = rel, k, ties == "any"
        self.best: list[tuple[tuple, FD]] = []
        self.tau = 1

    def offer(self, fd: FD) -> bool:
        """True if the answer changed. Without k, everything is kept, also what has no redundancy."""
        key = self.rel.sort_key(fd)
        if self.k is None:
            self.best.append((key, fd))
            return True
        if fd.redundancy < 1 or (len(self.best) == self.k and key > self.best[-1][0]):
            return False
        at = 0
        while at < len(self.best) and self.best[at][0] < key:
            at += 1
        self.best.insert(at, (key, fd))
        del self.best[self.k :]
        if len(self.best) == self.k:
            self.tau = max(1, self.best[-1][1].redundancy)
        return True

    def below(self, bound: int) -> bool:
        if self.k is None:
            return False
        return bound < self.tau or (self.any and len(self.best) == self.k and bound <= self.tau)

    def answer(self) -> list[FD]:
        return [fd for _, fd in sorted(self.best)]


@dataclass
class Discovery:
    """What a run gives: answer, counters, threshold trace, evidence, counts."""

    rel: Relation
    variant: str
    k: int | None
    fds: list[FD]
    stats: dict
    trace: list[tuple[int, float, int, int]]
    edges: set[int]
    cards: list[int]
    matrix: PairMatrix
    status: str = "complete"

    @property
    def result(self) -> DataFrame:
        return self.rel.frame(self.fds)

    def stats_frame(self) -> DataFrame:
        return self.rel.df.sparkSession.createDataFrame([tuple(self.stats[c.split()[0]] for c in STATS_SCHEMA.split(", "))], STATS_SCHEMA)

    def trace_frame(self) -> DataFrame:
        return self.rel.df.sparkSession.createDataFrame(self.trace, TRACE_SCHEMA)


@dataclass
class _Run:
    rel: Relation
    top: TopK
    n: int
    cards: list[int]
    order: list[int]
    matrix: PairMatrix
    edges: set[int]
    batch: int
    limits: Limits
    began: float
    counters: Counters = field(default_factory=Counters)
    validations: int = 0
    valid: int = 0
    valid_at_change: int = 0
    rounds: int = 0
    jobs: int = 0
    pairs_s: float = 0.0
    queue_s: float = 0.0
    trace: list = field(default_factory=list)
    sample: evidence.Sample | None = None
    unrefuted: set = field(default_factory=set)
    unsliced: set = field(default_factory=set)
    known: set = field(default_factory=set)
    sample_refuted: int = 0
    slice_refuted: int = 0
    cut: bool = False
    early: bool = True
    progress: Progress | None = None

    def over(self) -> bool:
        """Whether a limit is reached. A loop that has work left asks, so a run that ends just at a limit is complete."""
        x = self.limits
        self.cut = self.cut or bool(
            (x.max_validations is not None and self.validations >= x.max_validations)
            or (x.max_nodes is not None and self.counters.generated >= x.max_nodes)
            or (x.max_seconds is not None and time.monotonic() - self.began >= x.max_seconds)
        )
        return self.cut

    def mark(self) -> None:
        self.trace.append((len(self.trace), time.monotonic() - self.began, self.validations, self.top.tau))

    def refute_early(self, candidates: list[tuple[int, int]]) -> set[tuple[int, int]]:
        """Candidates that the driver's bounded sample of rows already refutes, at no job's cost; if there is none, those that a slice of the classes refutes.
        Their difference sets are added."""
        if not self.early:
            return set()
        out = self._refute_on_sample(candidates)
        one_in = min(MOST_SLICES, self.n // SLICE_ROWS)
        fresh = [c for c in candidates if c not in self.unsliced and c not in self.known]
        if out or one_in < 4 or not fresh or self.rel.held is not None or (self.sample is not None and one_in < MOST_SLICES):
            return out
        self.jobs += 1
        broken = cardinality.refute_on_slice(self.rel, fresh, one_in, self.cards)
        self.unsliced |= set(fresh) - set(broken)
        if broken:
            self.jobs += 1
            self.edges |= set(evidence.violating_edges(self.rel, [(lhs, a, x) for (lhs, a), x in broken.items()]).values())
            self.slice_refuted += len(broken)
        return set(broken)

    def _refute_on_sample(self, candidates: list[tuple[int, int]]) -> set[tuple[int, int]]:
        out = set()
        if self.sample is None or not len(self.sample):
            return out
        asked = [c for c in candidates if c not in self.unrefuted and c not in self.known]
        for c, found in zip(asked, evidence.refute_on_sample_all(self.sample, self.cards, asked), strict=True):
            if found:
                self.edges |= found
                out.add(c)
            else:
                self.unrefuted.add(c)
        self.sample_refuted += len(out)
        return out

    def accept(self, fd: FD) -> None:
        """A dependency that holds and is minimal."""
        self.known.add((fd.lhs, fd.rhs))
        self.valid += 1
        tau = self.top.tau
        if self.top.offer(fd):
            self.valid_at_change = self.valid
        if self.top.tau != tau:
            self.mark()

    def check(self, candidates: list[tuple[int, int]]) -> list[tuple[int, int]]:
        """Validates; offers what holds; adds the edges of what doesn't. Returns the refuted."""
        fresh = [c for c in candidates if c not in self.known]
        if not fresh:
            return []
        self.rounds += 1
        self.validations += len(fresh)
        if self.rel.held is not None:
            verdicts = {c: cardinality.Verdict(not edges, card, None, tuple(sorted(edges))) for c, (card, edges) in self.rel.held.check(fresh).items()}
        elif self.early and self.sample is not None and self.sample.whole:
            # a relation that the sample holds whole: the driver has all that Spark's check would read
            here = {(lhs, a): evidence.check_on_sample(self.sample, lhs, a) for lhs, a in fresh}
            verdicts = {c: cardinality.Verdict(not edges, card, None, tuple(sorted(edges))) for c, (card, edges) in here.items()}
        else:
            self.jobs += 1
            verdicts = cardinality.check_batch(self.rel, fresh)
        broken = []
        for lhs, a in fresh:
            v = verdicts[lhs, a]
            self.matrix.learn(lhs, v.n_classes)
            if v.valid:
                self.accept(FD(lhs, a, v.n_classes, self.n))
            else:
                broken.append((lhs, a, v))
        if broken:
            # without early evidence, one pair of rows a failure
            self.edges |= {e for _, _, v in broken for e in (v.edges if self.early else v.edges[:1])}
            if unseen := [(lhs, a, v.example) for lhs, a, v in broken if not v.edges]:
                self.jobs += 1
                self.edges |= set(evidence.violating_edges(self.rel, unseen).values())
        if self.progress is not None:
            self.progress.save(self)
        return [(lhs, a) for lhs, a, _ in broken]


@dataclass
class _Prepared:
    """What every run over a relation starts from: its profile and its evidence, the seconds that these took, and the heap's peak after them."""

    n: int
    cards: list[int]
    sample: evidence.Sample
    edges: set[int]
    held: Held | None = None
    seconds: float = 0.0
    peak_heap_mb: float = float("nan")


def _warm_start(run: _Run, max_lhs: int | None, empty_lhs: bool) -> None:
    """Constants and single attributes as left-hand sides first: m^2 candidates at most, of which the sample leaves few. What holds there is minimal, fills the answer
    with large redundancies, and so gives the search a threshold before it has to hold any larger set."""
    every = range(run.rel.m)
    constant = {a for a in every if run.cards[a] <= 1}
    found = [(run.n - 1, 0, a) for a in constant] if empty_lhs else []
    if max_lhs is None or max_lhs >= 1:
        left = [a for a in every if a not in constant or not empty_lhs]
        found += [(run.n - run.cards[x], 1 << x, a) for a in left for x in every if x != a and run.cards[x] >= run.cards[a]]
    found.sort(key=lambda f: (-f[0], f[1], f[2]))
    while found and not run.top.below(found[0][0]) and not run.over():
        batch, found = found[: 4 * run.batch], found[4 * run.batch :]
        batch = [(lhs, a) for bound, lhs, a in batch if not run.top.below(bound)]
        run.counters.generated += len(batch)
        run.counters.visited += len(batch)
        refuted = run._refute_on_sample(batch)
        run.check([c for c in batch if c not in refuted])


def _search_trees(run: _Run, scheduler: str, max_lhs: int | None, empty_lhs: bool, recheck: bool) -> None:
    rel, top = run.rel, run.top
    rank = [run.order.index(i) for i in range(rel.m)]
    trees = {a: Tree(a, rel.m, partial(evidence.induce, run.edges, a), rank, run.matrix, run.counters, max_lhs, empty_lhs) for a in run.order}
    for t in trees.values():
        t.recheck = recheck
    pending: list[tuple[int, int]] = []

    def settle() -> None:
        if not pending:
            return
        known = set(run.edges)
        valid: dict[int, set[int]] = {}
        if not run.refute_early(pending):
            broken = set(run.check(pending))
            run.counters.refuted += len(broken)
            for lhs, a in set(pending) - broken:
                valid.setdefault(a, set()).add(lhs)
        pending.clear()
        fresh = run.edges - known
        for a, t in trees.items():
            t.resume(valid.get(a, set()))
            if t.stack and fresh:
                t.add_edges(evidence.induce(fresh, a))

    def advance(a: int) -> None:
        lhs = trees[a].step(top.below)
        if lhs is not None:
            pending.append((lhs, a))
            if len(pending) >= run.batch:
                settle()

    def drain(some: Iterable[int]) -> None:
        for a in some:
            while trees[a].top_bound() is not None or any(b == a for _, b in pending):
                if run.over():
                    return
                if trees[a].top_bound() is None:
                    # the pending candidates of this tree may reopen it
                    settle()
                    continue
                advance(a)

    if scheduler == "sequential" and top.k is None and run.batch > 1:
        # nothing is pruned, so a round that one tree leaves open is filled up by the next ones
        while not run.over():
            a = next((a for a in run.order if trees[a].top_bound() is not None), None)
            if a is not None:
                advance(a)
            elif pending:
                settle()
            else:
                break
        return
    if scheduler == "sequential":
        drain(run.order)
        settle()
        drain(run.order)
        return
    began = time.monotonic()
    queue: list[tuple[int, int, int]] = []

    def push(a: int) -> None:
        b = trees[a].top_bound()
        if b is not None:
            heapq.heappush(queue, (-b, rank[a], a))

    for a in run.order:
        push(a)
    while queue or pending:
        if run.over():
            break
        if not queue:
            spent = time.monotonic()
            settle()
            began += time.monotonic() - spent
            queue.clear()
            for a in run.order:
                push(a)
            continue
        _, _, a = heapq.heappop(queue)
        if not trees[a].stack:
            continue
        held, spent = (run.rounds, run.sample_refuted, run.slice_refuted), time.monotonic()
        advance(a)
        if (run.rounds, run.sample_refuted, run.slice_refuted) != held:
            # a round may have reopened trees: bounds and tops are stale
            began += time.monotonic() - spent
            queue.clear()
            for b in run.order:
                push(b)
        else:
            push(a)
    run.queue_s = time.monotonic() - began


def _search_antichains(run: _Run, scheduler: str, max_lhs: int | None, empty_lhs: bool, spread: bool) -> bool:
    """False if the antichains outgrew their share of memory; what was settled stays settled."""
    rel, top = run.rel, run.top
    rank = [run.order.index(i) for i in range(rel.m)]
    most = MOST_SETS if run.limits.max_antichain is None else run.limits.max_antichain
    if spread:
        while found := spread_candidates(run, rank, max_lhs, empty_lhs, most):
            if run.over():
                return True
            chosen = [(lhs, a) for *_, lhs, a in found[: run.batch]]
            run.counters.visited += len(chosen)
            if not run.refute_early(chosen):
                run.check(chosen)
        return True
    chains: dict[int, Antichain] = {}

    def outgrown() -> bool:
        return sum(len(c.sets) for c in chains.values()) > most or any(c.overgrown for c in chains.values())

    for a in run.order:
        chains[a] = Antichain(a, rel.m, evidence.induce(run.edges, a), rank, run.matrix, run.counters, max_lhs, empty_lhs, top.below, most)
        chains[a].settled |= {lhs for lhs, b in run.known if b == a}
        if outgrown():
            return False

    def round_of(some: list[int]) -> bool:
        if outgrown():
            return False
        found = [(-bound, rank[a], lhs.bit_count(), lhs, a) for a in some for bound, lhs in chains[a].candidates(top.below)]
        if not found or run.over():
            return False
        chosen = [(lhs, a) for *_, lhs, a in heapq.nsmallest(run.batch, found)]
        run.counters.visited += len(chosen)
        known = set(run.edges)
        if not run.refute_early(chosen):
            broken = set(run.check(chosen))
            for lhs, a in chosen:
                if (lhs, a) not in broken:
                    chains[a].settled.add(lhs)
        fresh = run.edges - known
        for a, c in chains.items():
            c.add_edges(evidence.induce(fresh, a), top.below)
        return True

    if scheduler == "sequential":
        for a in run.order:
            while round_of([a]):
                pass
    else:
        while round_of(run.order):
            pass
    return not outgrown()


def discover(
    source: DataFrame | Relation,
    k: int | None = 10,
    variant: str = "full",
    *,
    columns: list[str] | None = None,
    order: str | None = None,
    bound: str | None = None,
    scheduler: str | None = None,
    kernel: str | None = None,
    batch: int | None = None,
    max_lhs: int | None = None,
    nulls: str = "eq",
    ties: str = "canonical",
    empty_lhs: bool = True,
    sample: bool = True,
    sample_bound: bool = True,
    slice_rows: int = evidence.SLICE_ROWS,
    early: bool = True,
    edges: set[int] | None = None,
    limits: Limits | None = None,
    persist: bool = False,
    strict_counts: bool = False,
    seed: int = 20,
    warm_start: bool | None = None,
    spread: bool = False,
    profile: str = "exact",
    recheck: bool = True,
    resume: str | None = None,
) -> Discovery:
    """The k dependencies of largest redundancy of a DataFrame; with k=None all minimal ones, by the same kernel without pruning.

    kernel: tree or antichain; without a choice, antichains where candidates are validated in batches, and the published trees one by one or without k.
    edges: stored difference sets of the same rows. batch: candidates of a round; 1 validates one by one. max_lhs: leave larger left-hand sides out. limits: end early with status over_budget.
    strict_counts: don't test a node's bound again when it is popped. sample_bound: also bound by the classes that a set has among the sampled rows.
    slice_rows: sampled rows of an attribute, at most. early: refute candidates on the sample and on slices before they are validated; without it, the sample gives no more than a few neighbours' difference sets.
    persist: keep the codes of a DataFrame while the search runs. warm_start: single attributes first (default: where batches are used).
    spread: the antichains are multiplied on the executors, one task a right-hand side. profile="lower": sketched lower estimates instead of exact
    counts of near-keys; the run then says that it isn't exact. recheck: the answer is counted again by raw values, and a difference is an error.
    resume: a folder that each round is appended to; a run over the same rows goes on from there."""
    if variant not in VARIANTS:
        raise ValueError(f"unknown variant {variant}")
    if kernel not in (None, "tree", "antichain"):
        raise ValueError(f"unknown kernel {kernel}")
    if profile not in ("exact", "lower"):
        raise ValueError(f"unknown profile {profile}")
    batch = batch if batch is not None else BATCH if k is None else max(BATCH, min(MOST_BATCH, k // 2))
    batched = batch > 1 and k is not None
    kernel = kernel or ("antichain" if batched else "tree")
    choice = VARIANTS[variant] | {x: v for x, v in (("order", order), ("bound", bound), ("scheduler", scheduler)) if v is not None}
    own = isinstance(source, DataFrame)
    rel = Relation.bind(source, columns, nulls, persist) if own else source
    top = TopK(rel, k, ties)
    meter = Meter(rel.df.sparkSession)
    began = time.monotonic()
    progress = Progress(rel, resume) if resume is not None else None
    held = progress.load() if progress is not None else None
    shared = None if held or profile != "exact" or not sample or edges is not None else getattr(rel, "shared", None)
    once = shared.get((slice_rows, seed, early)) if shared is not None else None
    if once is not None:
        began -= once.seconds
    rel.held = once.held if once is not None else None
    if once is None and getattr(rel, "hold", False) and not held and profile == "exact":
        if rel.holds is not None:
            began -= rel.holds[1]
            rel.held = rel.holds[0]
        else:
            spent = time.monotonic()
            rel.held = hold(rel, recheck)
            if rel.held is not None:
                spent, began = spent - rel.held.before, began - rel.held.before
            # what isn't counted raw is not kept for runs that want it so
            rel.holds = (rel.held, time.monotonic() - spent) if recheck else None
    if rel.held is not None:
        n, cards = rel.held.n, rel.held.cards
    elif held or once is not None:
        n, cards = (held or once).n, (held or once).cards
    elif profile == "lower" and rel.m:
        n, cards = cardinality.lower_profile(rel)
    else:
        n, cards = cardinality.profile(rel) if rel.m else (rel.df.count(), [])
    if profile == "exact":
        rel.counted = (n, cards)
    access = attribute_order(cards, choice["order"], seed)
    matrix = PairMatrix(n, cards, choice["bound"])
    run = _Run(rel, top, n, cards, access, matrix, set(edges or ()), max(1, batch), limits or Limits(), began, early=early, progress=progress)
    run.jobs = 0 if held else 2
    prepared = time.monotonic() - began
    if held:
        run.edges |= held.edges
        for mask, card in held.pairs.items():
            matrix.learn(mask, card)
        for fd in held.fds:
            run.accept(fd)
    if choice["bound"] != "single" and k is not None and not (held and held.pairs):
        spent = time.monotonic()
        matrix.precompute(rel, access)
        run.pairs_s = time.monotonic() - spent
        run.jobs += 1
    if sample and edges is None:
        spent = time.monotonic()
        run.sample = evidence.take_sample(rel, n, cards, slice_rows, seed) if once is None else once.sample
        if sample_bound and k is not None:
            matrix.sample = run.sample.rows[: evidence.COUNT_CELLS // max(1, rel.m)]
        if once is None:
            once = _Prepared(n, cards, run.sample, evidence.edges_of_sample(run.sample, evidence.SORTS if early else 0, seed) if len(run.sample) else set(), rel.held)
            once.seconds, once.peak_heap_mb = prepared + time.monotonic() - spent, meter.peak()
            if shared is not None:
                shared[slice_rows, seed, early] = once
        run.edges |= once.edges
        run.jobs += 2
    run.mark()
    if n:
        if (batched if warm_start is None else warm_start) and k is not None:
            _warm_start(run, max_lhs, empty_lhs)
        if kernel == "tree" or not _search_antichains(run, choice["scheduler"], max_lhs, empty_lhs, spread):
            _search_trees(run, choice["scheduler"], max_lhs, empty_lhs, not strict_counts)
    status = "over_budget" if run.cut else "complete"
    run.mark()
    answer = top.answer()
    # what is held was counted by its values when it was fetched
    if recheck and k is not None and rel.held is None and rel.df.sparkSession is not None and answer:
        if wrong := cardinality.recheck(rel, [(f.lhs, f.rhs, f.n_classes) for f in answer]):
            raise RuntimeError(f"codes and raw values disagree on {wrong}")
        run.jobs += 1
    c = run.counters
    stats = {
        "variant": variant if k is not None else "exhaustive", "k": k or 0, "n_rows": n, "n_attributes": rel.m, "status": status, "nodes_generated": c.generated, "nodes_visited": c.visited,
        "validations": run.validations, "valid_found": run.valid, "valid_until_last_change": run.valid_at_change, "pruned_expand": c.pruned_expand, "pruned_validate": c.pruned_validate,
        "pruned_pop": c.pruned_pop, "edges": len(run.edges), "sample_refuted": run.sample_refuted, "slice_refuted": run.slice_refuted, "rounds": run.rounds, "spark_jobs": run.jobs, "wall_s": time.monotonic() - began, "pairs_s": run.pairs_s, "queue_s": run.queue_s,
        "exact": profile == "exact",
    } | meter.read()
    if once is not None and once.peak_heap_mb > stats["peak_heap_mb"]:
        stats["peak_heap_mb"] = once.peak_heap_mb
    if own:
        rel.release()
    return Discovery(rel, variant, k, answer, stats, run.trace, run.edges, cards, matrix, status)


def holding(rel: Relation, lhs: list[str], rhs: str) -> bool:
    """Whether one dependency holds."""
    a = mask_of([rhs], rel.columns).bit_length() - 1
    lhs_mask = mask_of(lhs, rel.columns)
    return cardinality.check_batch(rel, [(lhs_mask, a)])[lhs_mask, a].valid


__all__ = ["BATCH", "FD_SCHEMA", "VARIANTS", "Discovery", "TopK", "discover", "holding"]
