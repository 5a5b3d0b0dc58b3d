"""Progress of a search, appended round by round to a shared folder, so that a run whose driver was lost goes on from there."""

from __future__ import annotations

import json
from dataclasses import dataclass, field

from pyspark.errors import AnalysisException

from ..model import FD, Relation
from ..operators.evidence import snapshot

SCHEMA = "snapshot string, body string"


@dataclass
class Held:
    """What is known of the rows: numbers of classes, difference sets, dependencies that hold. None of it depends on k or the variant."""

    n: int
    cards: list[int]
    edges: set[int] = field(default_factory=set)
    pairs: dict[int, int] = field(default_factory=dict)
    fds: list[FD] = field(default_factory=list)


class Progress:
    def __init__(self, rel: Relation, folder: str):
        self.rel, self.folder, self.mark = rel, folder, snapshot(rel)
        self.edges: set[int] = set()
        self.pairs: set[int] = set()
        self.fds: set[tuple[int, int]] = set()

    def load(self) -> Held | None:
        """None if the folder holds nothing of these rows."""
        try:
            rows = self.rel.df.sparkSession.read.schema(SCHEMA).parquet(self.folder).where(f"snapshot = '{self.mark}'").collect()
        except AnalysisException:
            return None
        held = None
        for r in rows:
            body = json.loads(r["body"])
            held = held or Held(body["n"], body["cards"])
            held.edges |= {int(e, 16) for e in body["edges"]}
            held.pairs |= {int(m, 16): c for m, c in body["pairs"].items()}
            held.fds += [FD(int(x, 16), a, c, held.n) for x, a, c in body["fds"]]
        if held:
            held.fds = sorted({(f.lhs, f.rhs): f for f in held.fds}.values(), key=self.rel.sort_key)
            self.edges, self.pairs, self.fds = set(held.edges), set(held.pairs), {(f.lhs, f.rhs) for f in held.fds}
        return held

    def save(self, run) -> None:
        """What this round added."""
        known = {(f.lhs, f.rhs): f.n_classes for _, f in run.top.best}
        body = {
            "n": run.n, "cards": run.cards, "edges": [hex(e) for e in run.edges - self.edges], "pairs": {hex(m): c for m, c in run.matrix.pairs.items() if m not in self.pairs},
            "fds": [(hex(x), a, c) for (x, a), c in known.items() if (x, a) not in self.fds],
        }
        self.edges |= run.edges
        self.pairs |= set(run.matrix.pairs)
        self.fds |= set(known)
        self.rel.df.sparkSession.createDataFrame([(self.mark, json.dumps(body))], SCHEMA).coalesce(1).write.mode("append").parquet(self.folder)
