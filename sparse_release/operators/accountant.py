"""The privacy ledger: what each release cost, and what of the budget is left."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

_ROW = "release string, eps double, delta double, part string, note string, digest string"


@dataclass
class Accountant:
    """Costs add up; releases over disjoint parts of the data (same group, different parts) cost as much as the dearest of them."""

    budget: float
    delta_budget: float = 0.0
    entries: list[tuple[str, float, float, str | None, str, str]] = field(default_factory=list)

    def spend(self, release: str, eps: float, delta: float = 0.0, part: str | None = None, note: str = "", digest: str = "") -> float:
        """Enters a release; fails if it would overdraw. part: "group/part" for one of disjoint parts. digest: of whatever makes the release what it is (data, domain, method).
        A release that is entered already costs nothing more if all of this is the same, for then its numbers are; a name that is used again for anything else fails."""
        if eps < 0 or delta < 0:
            raise ValueError("costs are not negative")
        entry = (release, float(eps), float(delta), part, note, digest)
        for e in self.entries:
            if e[0] == release:
                if (e[1], e[2], e[3], e[5]) != (entry[1], entry[2], part, digest):
                    raise ValueError(f"{release} is the name of another release: its draws must not be used again")
                return self.left()
        if self._total([*self.entries, entry], 1) > self.budget + 1e-12 or self._total([*self.entries, entry], 2) > self.delta_budget + 1e-15:
            raise ValueError(f"{release} would overdraw the budget: {self.left()} is left")
        self.entries.append(entry)
        return self.left()

    @staticmethod
    def _total(entries: list[tuple], k: int) -> float:
        alone = sum(e[k] for e in entries if e[3] is None)
        groups: dict[str, dict[str, float]] = {}
        for e in entries:
            if e[3] is not None:
                group, _, part = e[3].partition("/")
                groups.setdefault(group, {}).setdefault(part, 0.0)
                groups[group][part] += e[k]
        return alone + sum(max(g.values()) for g in groups.values())

    def spent(self) -> float:
        return self._total(self.entries, 1)

    def left(self) -> float:
        return self.budget - self.spent()

    def table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.entries, _ROW)

    def append_to(self, spark: SparkSession, path: str) -> None:
        """Appends the entries to a ledger of Parquet files."""
        self.table(spark).write.mode("append").parquet(path)

    @classmethod
    def read(cls, spark: SparkSession, path: str, budget: float, delta_budget: float = 0.0) -> Accountant:
        return cls(budget, delta_budget, [tuple(r) for r in spark.read.parquet(path).distinct().orderBy("release").collect()])
