"""Conjunctive queries: equi-joins of datasets under set semantics, made from discovered predicates."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Predicate:
    left_dataset: str
    left_attr: str
    right_dataset: str
    right_attr: str

    @classmethod
    def of(cls, row) -> "Predicate":
        return cls(row["ref_dataset"], row["ref_attr"], row["cand_dataset"], row["cand_attr"])


@dataclass
class CQ:
    """Datasets, predicates between them, and projected (dataset, attr) pairs; every attribute comes out as dataset__attr."""

    datasets: list[str]
    predicates: list[Predicate]
    projection: list[tuple[str, str]] = field(default_factory=list)

    def _columns(self, frames: dict[str, DataFrame]) -> list[tuple[str, str]]:
        return self.projection or [(d, c) for d in self.datasets for c in frames[d].columns]

    def _order(self, size: dict[str, int] | None) -> list[str]:
        """Datasets so that each is linked to one before it where any link exists, small ones first if sizes are known."""
        key = lambda d: (size or {}).get(d, 0)
        left = sorted(self.datasets, key=key) if size else list(self.datasets)
        done = [left.pop(0)]
        while left:
            linked = [d for d in left if any({p.left_dataset, p.right_dataset} & {d} and {p.left_dataset, p.right_dataset} & set(done) for p in self.predicates)]
            done.append(linked[0] if linked else left[0])
            left.remove(done[-1])
        return done

    def _read(self, frames: dict[str, DataFrame], d: str) -> DataFrame:
        """The columns of a dataset that the query needs, as a set."""
        named = {c for x, c in self._columns(frames) if x == d} | {p.left_attr for p in self.predicates if p.left_dataset == d} | {p.right_attr for p in self.predicates if p.right_dataset == d}
        return frames[d].select(*[F.col(f"`{c}`").alias(f"{d}__{c}") for c in frames[d].columns if c in named]).distinct()

    def _determined(self, out: DataFrame, shown: list[str]) -> bool:
        """Whether each column of the joined sets is shown, or equal to one that is and of its type: then no row comes twice."""
        types, known = dict(out.dtypes), set(shown)
        pairs = [(f"{p.left_dataset}__{p.left_attr}", f"{p.right_dataset}__{p.right_attr}") for p in self.predicates]
        for _ in pairs:
            known |= {x for a, b in pairs if types[a] == types[b] and {a, b} & known for x in (a, b)}
        return set(out.columns) <= known

    def run(self, frames: dict[str, DataFrame], size: dict[str, int] | None = None) -> DataFrame:
        """Joins of sets in sequence; a product is left only where no predicate links a dataset. Catalyst reorders and prunes. Rows are
        made distinct before they multiply, and after the joins only where a column that is left out can make them alike."""
        order, out, seen = self._order(size), None, set()
        for d in order:
            frame = self._read(frames, d)
            mine = [p for p in self.predicates if {p.left_dataset, p.right_dataset} <= seen | {d} and d in (p.left_dataset, p.right_dataset)]
            on = [F.col(f"`{p.left_dataset}__{p.left_attr}`") == F.col(f"`{p.right_dataset}__{p.right_attr}`") for p in mine]
            out = frame if out is None else out.crossJoin(frame) if not on else out.join(frame, on)
            seen.add(d)
        shown = [f"{d}__{c}" for d, c in self._columns(frames)]
        rows = out.select(*[F.col(f"`{c}`") for c in shown])
        return rows if self._determined(out, shown) else rows.distinct()

    def to_sql(self, frames: dict[str, DataFrame]) -> str:
        select = ", ".join(f"{d}.{c} AS {d}__{c}" for d, c in self._columns(frames))
        on = " AND ".join(f"{p.left_dataset}.{p.left_attr} = {p.right_dataset}.{p.right_attr}" for p in self.predicates)
        return f"SELECT DISTINCT {select} FROM {', '.join(self.datasets)}" + (f" WHERE {on}" if on else "")


def from_predicate(p: Predicate, frames: dict[str, DataFrame], left: Column | None = None, right: Column | None = None) -> DataFrame:
    """The join a predicate stands for. ``left`` and ``right`` join on transformed attributes instead."""
    if left is None and right is None:
        return CQ([p.left_dataset, p.right_dataset], [p]).run(frames)
    a = frames[p.left_dataset].withColumn("_k", left if left is not None else F.col(p.left_attr))
    b = frames[p.right_dataset].withColumn("_k", right if right is not None else F.col(p.right_attr))
    a = a.select("_k", *[F.col(c).alias(f"{p.left_dataset}__{c}") for c in frames[p.left_dataset].columns])
    b = b.select("_k", *[F.col(c).alias(f"{p.right_dataset}__{c}") for c in frames[p.right_dataset].columns])
    return a.join(b, "_k").drop("_k").distinct()
