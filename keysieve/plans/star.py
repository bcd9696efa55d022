"""Star queries: every relation's scan is reduced by the sketches of all others before anything is joined.

A relation's own predicate, also a range, is evaluated exactly by its own scan. Other relations see it through a
sketch: equalities as they are, ranges as in-lists of bins. All relations joined on one key, also through
transitive equalities, filter each other.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import Predicate
from ..operators import probe as R
from ..operators.pairs import Sketch
from ..sources import tables as S


@dataclass
class Relation:
    """A DataFrame with key column k, its exact own predicate as SQL, and what sketches can say of it."""

    name: str
    rows: DataFrame
    own: str = "true"
    pred: Predicate = field(default_factory=Predicate)

    def scan(self) -> DataFrame:
        return self.rows.filter(self.own)


@dataclass
class StarQuery:
    relations: list[Relation]


def equality_closure(equalities: list[tuple[str, str]]) -> dict[str, str]:
    """The class of each column under equalities, named by its smallest member."""
    parent: dict[str, str] = {}

    def find(x: str) -> str:
        parent.setdefault(x, x)
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for a, b in equalities:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return {x: find(x) for x in parent}


class SketchCatalog:
    """Sketches by relation, joint or of single attributes; `live` gives a relation's key filters under a predicate."""

    def __init__(self) -> None:
        self.sketches: dict[str, list[Sketch]] = {}
        self.closures: dict[int, DataFrame] = {}

    def put(self, relation: str, sketch: Sketch) -> None:
        self.sketches.setdefault(relation, []).append(sketch)

    def live(self, relation: str, pred: Predicate) -> list[tuple[Sketch, DataFrame]]:
        """Filters of all sketches that know an attribute of the predicate; without any, the keys of the first sketch."""
        own = self.sketches.get(relation, [])
        used = [s for s in own if {a.name for a in s.spec.attrs} & set(pred.allowed)]
        out = []
        for s in used or own[:1]:
            if s.spec.variant == "chained" and id(s) not in self.closures:
                self.closures[id(s)] = R.close(s)
            out.append((s, R.derive_key_filter(s, pred, self.closures.get(id(s)))))
        return out

    def stored(self) -> SketchCatalog:
        """The same sketches written to the shared folder, chained ones with their closures, so that queries only read them."""
        out = SketchCatalog()
        for relation, own in self.sketches.items():
            for sketch in own:
                kept = S.stored(sketch)
                out.put(relation, kept)
                if sketch.spec.variant == "chained":
                    out.closures[id(kept)] = S.save_filter(R.flat(R.close(kept), kept.spec), f"{S.shared_dir(kept.entries.sparkSession)}/closure")
        return out


def reduce(query: StarQuery, catalog: SketchCatalog) -> dict[str, DataFrame]:
    """Each relation's scan with its own predicate and every other relation's filters."""
    filters = {r.name: catalog.live(r.name, r.pred) for r in query.relations}
    out = {}
    for r in query.relations:
        rows = r.scan()
        for other in query.relations:
            if other.name != r.name:
                for sketch, live in filters[other.name]:
                    rows = R.semi(rows, "k", live, sketch.spec)
        out[r.name] = rows
    return out


def plan_join(query: StarQuery, catalog: SketchCatalog | None = None) -> DataFrame:
    """The join of all relations on k, over reduced scans if there is a catalog; columns are prefixed by their relation."""
    scans = reduce(query, catalog) if catalog else {r.name: r.scan() for r in query.relations}
    out = None
    for name, rows in scans.items():
        own = rows.select("k", *(F.col(c).alias(f"{name}_{c}") for c in rows.columns if c != "k"))
        out = own if out is None else out.join(own, "k")
    return out


def exact_semijoin(query: StarQuery, exact: bool = True) -> dict[str, DataFrame]:
    """The least that each scan can give: rows whose key is in every other relation under its own predicate."""
    out = {}
    for r in query.relations:
        rows = r.scan()
        for other in query.relations:
            if other.name != r.name:
                rows = rows.join(other.scan().select("k").distinct(), "k", "left_semi")
        out[r.name] = rows
    return out


def counts(parts: dict[str, DataFrame], name: str) -> DataFrame:
    """(rel, n) of several relations in one result."""
    out = None
    for rel, rows in parts.items():
        one = rows.agg(F.count("*").alias(name)).select(F.lit(rel).alias("rel"), name)
        out = one if out is None else out.unionByName(one)
    return out
