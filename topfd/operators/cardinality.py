"""Numbers of classes of attribute sets: the kernel that everything which touches all rows is made of.

`set_cardinalities` counts many sets in few jobs. Sets that share columns go into one grouping-sets job (an Expand, a partial
aggregation, one shuffle of partial groups, and a second, tiny one of counts); sets of few distinct values collapse before the shuffle. A job's sets
touch at most 60 columns, Spark's limit being 64, and at most `expand` sets, which bounds the rows that Expand makes.

`check_batch` decides candidates over codes of the values: narrow rows of 64-bit numbers whatever the columns' types, so what is
grouped and shuffled is small and codegen stays in hash aggregation. `recheck` counts an answer again by the raw values.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import Relation, bits
from . import local_classes

EXPAND, MOST_COLUMNS = 24, 60


def plan_jobs(sets: Iterable[int], expand: int = EXPAND, most_columns: int = MOST_COLUMNS) -> list[list[int]]:
    """Groups of sets for one job each: neighbours in bit order share columns, so scans stay narrow."""
    jobs: list[list[int]] = []
    union = 0
    for s in sorted(set(sets)):
        if jobs and len(jobs[-1]) < expand and (union | s).bit_count() <= most_columns:
            jobs[-1].append(s)
            union |= s
        else:
            jobs.append([s])
            union = s
    return jobs


def _null_free(rel: Relation, mask: int) -> Column:
    return reduce(lambda a, b: a & b, [c.isNotNull() for c in rel.cols(mask)], F.lit(True))


def grouping_frame(rel: Relation, sets: list[int], rows: DataFrame | None = None) -> DataFrame:
    """One job's plan: gid (the grouping id of the set over the job's columns), card, redundancy (sum of class size - 1)."""
    union = reduce(lambda a, b: a | b, sets)
    df = rel.df if rows is None else rows
    classes = df.groupingSets([rel.cols(s) for s in sets], *rel.cols(union)).agg(F.grouping_id().alias("gid"), F.count(F.lit(1)).alias("size"))
    return classes.groupBy("gid").agg(F.count(F.lit(1)).alias("card"), F.sum(F.col("size") - 1).alias("redundancy"))


def grouping_ids(sets: list[int]) -> dict[int, int]:
    """The grouping id that Spark gives each set: a bit is 1 if the column is *not* in the set, the first column highest."""
    union = reduce(lambda a, b: a | b, sets)
    columns = list(bits(union))
    return {sum(1 << (len(columns) - 1 - k) for k, i in enumerate(columns) if not s >> i & 1): s for s in sets}


def set_cardinalities(rel: Relation, sets: Iterable[int], expand: int = EXPAND) -> dict[int, int]:
    """Exact number of classes of each set."""
    wanted = set(sets)
    found: dict[int, int] = {}
    if 0 in wanted:
        wanted.discard(0)
        found[0] = int(rel.df.limit(1).count())
    if rel.nulls == "neq":
        # a row with a null in a set is a class of its own
        for s in wanted:
            whole = rel.df.where(_null_free(rel, s)).select(*rel.cols(s)).distinct().agg(F.count(F.lit(1)).alias("c"))
            found[s] = whole.first()["c"] + rel.df.where(~_null_free(rel, s)).count()
        return found
    for job in plan_jobs(wanted, expand):
        ids = grouping_ids(job)
        found |= {ids[r["gid"]]: r["card"] for r in grouping_frame(rel, job, rel.rows).collect()}
        found |= {s: 0 for s in job if s not in found}
    return found


def exploded_cardinalities(rel: Relation, sets: list[int]) -> dict[int, int]:
    """The other kernel: one array of (set, fingerprint) pairs a row, exploded. For sets over more columns than grouping sets take; exact up to 128-bit collisions."""
    pairs = F.array(*[F.struct(F.lit(k).alias("s"), rel.fingerprint(s, 1).alias("a"), rel.fingerprint(s, 2).alias("b")) for k, s in enumerate(sets)])
    counted = rel.df.select(F.explode(pairs).alias("p")).select("p.*").distinct().groupBy("s").count()
    got = {sets[r["s"]]: r["count"] for r in counted.collect()}
    return {s: got.get(s, 0) for s in sets}


def _union_all(frames: list[DataFrame]) -> DataFrame:
    """One union. Spark analyses and flattens it at every step, so halves are united, not one frame after the other."""
    while len(frames) > 1:
        frames = [a.unionAll(b) for a, b in zip(frames[::2], frames[1::2], strict=False)] + frames[len(frames) // 2 * 2 :]
    return frames[0]


def coded_cardinalities(rel: Relation, sets: Iterable[int]) -> dict[int, int]:
    """The kernel of the search: number of classes of each set by 128-bit keys over codes, one branch a set, so a job reads only the columns of its sets and
    a task's hash table holds one set. Exact up to 128-bit collisions; answers are counted again by raw values."""
    wanted = list(dict.fromkeys(sets))
    if rel.held is not None:
        return rel.held.cardinalities(wanted)
    found = {0: int(rel.coded.limit(1).count())} if 0 in wanted else {}
    wanted = [s for s in wanted if s]
    per_job = _sets_in_a_job(rel)
    for at in range(0, len(wanted), per_job):
        some = wanted[at : at + per_job]
        keyed = [rel.coded.selectExpr(f"{k} AS s", *(f"{x} AS x{i}" for i, x in enumerate(rel.key_sql(s), 1))) for k, s in enumerate(some)]
        counted = _union_all(keyed).distinct().groupBy("s").count()
        found |= dict.fromkeys(some, 0) | {some[r["s"]]: r["count"] for r in counted.collect()}
    return found


def profile(rel: Relation) -> tuple[int, list[int]]:
    """(rows, classes of each attribute)."""
    cards = coded_cardinalities(rel, [1 << i for i in range(rel.m)])
    return rel.coded.count(), [cards[1 << i] for i in range(rel.m)]


def approximate_profile(rel: Relation, error: float = 0.02) -> list[int]:
    """Sketched numbers of classes, one narrow pass without a wide shuffle."""
    row = rel.coded.agg(*[F.approx_count_distinct(f"_1_{i}", error).alias(f"c{i}") for i in range(rel.m)]).first()
    return [row[f"c{i}"] or 0 for i in range(rel.m)]


def lower_profile(rel: Relation, error: float = 0.02, margin: float = 4.0) -> tuple[int, list[int]]:
    """(rows, lower estimates of the classes of each attribute) without the shuffle of near-keys: sketches less `margin` standard errors. Pruning needs no more than
    a lower bound, but these hold with high probability only, so a run that uses them says it isn't exact."""
    return rel.coded.count(), [max(1, int(c * (1 - margin * error))) if c else 0 for c in approximate_profile(rel, error)]


@dataclass(frozen=True)
class Verdict:
    valid: bool
    n_classes: int
    example: tuple[int | Column, int | Column] | None  # fingerprints of a class of the left-hand side that breaks the dependency, as numbers or as what gives them
    edges: tuple[int, ...] = ()  # difference sets that break it, where they were found on the way


#: Sets in one job, tasks of one job that read them, and right-hand sides that a class keeps.
SETS_IN_A_JOB, TASKS_IN_A_JOB, VALUES_IN_A_CLASS = 64, 100_000, 3


def _sets_in_a_job(rel: Relation) -> int:
    """Every set is a branch with a task for each partition; a job's tasks are bounded whatever the number of rows."""
    return max(1, min(SETS_IN_A_JOB, TASKS_IN_A_JOB // max(1, rel.partitions())))


def _plan_checks(rel: Relation, candidates: Iterable[tuple[int, int]]) -> list[list[tuple[int, list[int]]]]:
    by_lhs: dict[int, list[int]] = {}
    for lhs, a in dict.fromkeys(candidates):
        by_lhs.setdefault(lhs, []).append(a)
    entries = [(lhs, rhs[i : i + VALUES_IN_A_CLASS]) for lhs, rhs in sorted(by_lhs.items()) for i in range(0, len(rhs), VALUES_IN_A_CLASS)]
    per_job = _sets_in_a_job(rel)
    return [entries[i : i + per_job] for i in range(0, len(entries), per_job)]


def check_frame(rel: Relation, entries: list[tuple[int, list[int]]], one_in: int = 1, cards: list[int] | None = None) -> DataFrame:
    """s (place in entries), card, and for each right-hand side the two key halves of a class that breaks it (null if none does).

    Each entry is a branch that reads its own columns alone and gives narrow rows: the key of its class, 128 bits, and the codes of the right-hand values. Classes
    keep minimum and maximum of each, all of them 64-bit numbers, so both aggregations stay hash aggregations that combine before the shuffle, and
    a task's hash table holds one entry's classes. one_in: only that part of the classes, whole; by cards, the attribute of the left-hand side
    with most classes decides, so a row that isn't of the slice is dropped before any key is built."""
    width = max(len(rhs) for _, rhs in entries)
    branches = []
    for k, (lhs, rhs) in enumerate(entries):
        rows = rel.coded
        if one_in > 1 and lhs:
            lead = max(bits(lhs), key=lambda i: cards[i] if cards else 0)
            rows = rows.where(f"pmod(xxhash64(_2_{lead}, 7), {one_in}) = 0")
        values = [f"_1_{a}" for a in rhs] + ["CAST(NULL AS BIGINT)"] * (width - len(rhs))
        # as text: a plan of many branches is built by one call a branch
        branches.append(rows.selectExpr(f"{k} AS s", *(f"{x} AS x{i}" for i, x in enumerate(rel.key_sql(lhs), 1)), *(f"{v} AS v{i}" for i, v in enumerate(values))))
    rows = _union_all(branches)
    classes = rows.groupBy("s", "x1", "x2").agg(*[f(f"v{i}").alias(f"{n}{i}") for i in range(width) for f, n in ((F.min, "lo"), (F.max, "hi"))])
    # both halves of an example are first values under one condition, hence of one class
    examples = [F.first(F.when(F.col(f"lo{i}") != F.col(f"hi{i}"), F.col(x)), ignorenulls=True).alias(f"{x}_{i}") for i in range(width) for x in ("x1", "x2")]
    return classes.groupBy("s").agg(F.count(F.lit(1)).alias("card"), *examples)


def _check_locally(rel: Relation, candidates: list[tuple[int, int]]) -> dict[tuple[int, int], Verdict]:
    """Those whose left-hand sides have classes enough to deal rows out by, in one job. Dealing pays off where several share it, so one alone is left to others."""
    by_lhs: dict[int, list[int]] = {}
    for lhs, a in dict.fromkeys(candidates):
        by_lhs.setdefault(lhs, []).append(a)
    if len(by_lhs) < 2:
        return {}
    entries = sorted(by_lhs.items())
    rows, _ = local_classes.verdict_rows(rel, entries, *rel.counted)
    found = {}
    for (s, i), (card, edges, codes) in rows.items():
        lhs, rhs = entries[s]
        example = None
        if edges or codes:
            half = len(codes) // 2 if codes else 0
            example = tuple(F.expr(f"xxhash64({', '.join([str(lhs.bit_count()), *(f'{c}L' for c in x)])})") for x in (codes[:half], codes[half:])) if codes else ()
        found[lhs, rhs[i]] = Verdict(example is None, card, example or None, edges)
    return found


def check_batch(rel: Relation, candidates: Iterable[tuple[int, int]]) -> dict[tuple[int, int], Verdict]:
    """Decides (lhs, attribute) candidates. Where the relation's class counts are known, left-hand sides with many classes are checked where their classes lie together;
    the others in one job for up to SETS_IN_A_JOB left-hand sides."""
    candidates = list(candidates)
    found = _check_locally(rel, candidates) if rel.counted is not None else {}
    for entries in _plan_checks(rel, [c for c in candidates if c not in found]):
        rows = {r["s"]: r for r in check_frame(rel, entries).collect()}
        for k, (lhs, rhs) in enumerate(entries):
            for i, a in enumerate(rhs):
                r = rows.get(k)
                broken = r is not None and r[f"x1_{i}"] is not None
                found[lhs, a] = Verdict(not broken, r["card"] if r else 0, (r[f"x1_{i}"], r[f"x2_{i}"]) if broken else None)
    return found


def recheck(rel: Relation, fds: Iterable[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """(lhs, attribute, n_classes) of an answer, counted once more by raw values: those that don't agree. A left-hand side is counted alone and with all
    its right-hand sides together, which agree just if each of them follows; only where they don't, one by one."""
    fds = list(fds)
    together: dict[int, int] = {}
    for lhs, a, _ in fds:
        together[lhs] = together.get(lhs, 0) | 1 << a
    card = set_cardinalities(rel, {s for lhs, rhs in together.items() for s in (lhs, lhs | rhs)})
    wrong = [(lhs, a, n) for lhs, a, n in fds if not card[lhs] == card[lhs | together[lhs]] == n]
    if wrong:
        card |= set_cardinalities(rel, {s for lhs, a, _ in wrong for s in (lhs, lhs | 1 << a)})
    return [(lhs, a, n) for lhs, a, n in wrong if not card[lhs] == card[lhs | 1 << a] == n]


def refute_on_slice(rel: Relation, candidates: Iterable[tuple[int, int]], one_in: int, cards: list[int] | None = None) -> dict[tuple[int, int], tuple[int, int]]:
    """Candidates that already fail on a slice of the classes, each with a class that breaks it. A slice keeps whole classes of each left-hand side, so a violation
    there is one of the relation; what survives needs the full pass. Only 1/one_in of the rows get a key."""
    broken = {}
    for entries in _plan_checks(rel, candidates):
        for r in check_frame(rel, entries, one_in, cards).collect():
            lhs, rhs = entries[r["s"]]
            broken |= {(lhs, a): (r[f"x1_{i}"], r[f"x2_{i}"]) for i, a in enumerate(rhs) if r[f"x1_{i}"] is not None}
    return broken
