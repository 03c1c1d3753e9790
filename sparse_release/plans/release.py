"""The user's way to a release: declare, choose a method, run, ask.

Noise is a function of a secret seed and the release's name, so both must be given: who knows them can subtract the noise, and two tables released under one name have
their difference published. Draws are by SHA-2; the other modes are for tests and must be asked for with testing=True.
"""

from __future__ import annotations

import hashlib
import json
import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame

from ..functions.durable import durable
from ..functions.laws import advise_cut, pick_cut, pick_tau
from ..functions.noise import alpha_of, moments
from ..operators import estimators as E
from ..operators import summaries as S
from ..operators.accountant import Accountant
from ..operators.contingency import bound_contributions, contingency
from ..operators.domain import Domain


@dataclass(frozen=True)
class Released:
    """A published summary and what may be said of it. It holds noised data only, so whatever is done with it costs no more privacy."""

    summary: DataFrame
    domain: Domain
    meta: dict

    def point(self, cells: DataFrame) -> DataFrame:
        return E.est_point(self.summary, cells)

    def range(self, queries: DataFrame) -> DataFrame:
        return E.est_range(self.summary, queries)

    def subset(self, members: DataFrame) -> DataFrame:
        return E.est_subset(self.summary, members)

    def where(self, condition: str) -> DataFrame:
        return E.est_where(self.summary, self.domain, condition)

    def group_by(self, *dims: str) -> DataFrame:
        return E.est_group_by(self.summary, self.domain, list(dims))

    def top(self, k: int) -> DataFrame:
        return E.est_top(self.summary, k)

    def variance(self, members: DataFrame) -> DataFrame:
        return E.est_variance(self.summary, members, self.meta.get("tau", 0.0), moments(self.meta["alpha"])["variance"])

    def create_view(self, name: str) -> None:
        """released_<name>, with decoded dimensions and weight, for plain SUM(weight)."""
        self.domain.decode(self.summary).createOrReplaceTempView(f"released_{name}")

    def write(self, path: str) -> None:
        """Parquet in order of cells, so that neither rows' order nor their files tell which cells were occupied; meta beside it."""
        rows = self.domain.decode(self.summary.select("cell_id", "value", "weight"))
        rows.repartitionByRange("cell_id").sortWithinPartitions("cell_id").write.mode("errorifexists").parquet(f"{path}/summary")
        self.summary.sparkSession.createDataFrame([(json.dumps(self.meta, sort_keys=True),)], "meta string").coalesce(1).write.text(f"{path}/meta")


METHODS = ("high_pass", "threshold", "priority", "filter_threshold", "filter_priority", "uniform", "full")


@dataclass(frozen=True)
class ReleasePlan:
    """Built up step by step: release(df).over(domain).epsilon(0.1).method("filter_priority", cut=40, s=100000).run()."""

    rows: DataFrame
    domain: Domain | None = None
    eps: float = 0.0
    how: str = "filter_priority"
    params: dict = field(default_factory=dict)
    measure: Column | None = None
    options: dict = field(default_factory=dict)
    bound: tuple[str, int, str] | None = None

    def over(self, domain: Domain) -> ReleasePlan:
        return ReleasePlan(**{**self.__dict__, "domain": domain})

    def epsilon(self, eps: float) -> ReleasePlan:
        return ReleasePlan(**{**self.__dict__, "eps": eps})

    def sum_of(self, measure: Column) -> ReleasePlan:
        return ReleasePlan(**{**self.__dict__, "measure": measure})

    def method(self, name: str, **params) -> ReleasePlan:
        if name not in METHODS:
            raise ValueError(f"method must be one of {METHODS}")
        return ReleasePlan(**{**self.__dict__, "how": name, "params": params})

    def each(self, person: str, rows: int, key: str) -> ReleasePlan:
        """At most so many rows of each person (drawn by a hash of key) are counted, and noise is for that many. Without it, a row is an individual."""
        return ReleasePlan(**{**self.__dict__, "bound": (person, rows, key)})

    def using(self, **options) -> ReleasePlan:
        """seed and release (a secret, and a name that no other data have had); sensitivity, route, way, blocks, mode of the draws, testing."""
        return ReleasePlan(**{**self.__dict__, "options": {**self.options, **options}})

    def run(self, ledger: Accountant | None = None) -> Released:
        if self.domain is None or self.eps <= 0:
            raise ValueError("a release needs a domain and a budget")
        options = {"mode": "sha2", **self.options}
        testing = options.pop("testing", False)
        if not {"seed", "release"} <= options.keys():
            raise ValueError("a release needs a secret seed and a name of its own")
        if options["mode"] != "sha2" and not testing:
            raise ValueError("draws that can be guessed are for tests only")
        rows = self.rows
        if self.bound is not None:
            person, most, key = self.bound
            rows = bound_contributions(rows, person, most, key, options["seed"], options["mode"])
            options["sensitivity"] = options.get("sensitivity", 1.0) * most
        plan = S.Plan(m=self.domain.size, eps=self.eps, **options)
        cells = durable(contingency(rows, self.domain, self.measure))  # read for the occupied part and for the empty one
        if ledger is not None:
            data = cells.selectExpr("count(*)", "sum(CAST(xxhash64(cell_id, v) AS DECIMAL(38, 0)))").first()
            told = repr((tuple(data), self.domain, self.how, sorted(self.params.items()), plan))
            ledger.spend(plan.release, self.eps, digest=hashlib.sha256(told.encode()).hexdigest())
        meta = {"eps": self.eps, "sensitivity": plan.sensitivity, "alpha": plan.alpha, "m": plan.m, "method": self.how, "release": plan.release, "route": plan.route, "way": plan.way, **self.params}
        p = self.params
        match self.how:
            case "high_pass":
                out = S.high_pass(cells, plan, p["cut"], p.get("sides", 2))
            case "threshold":
                out = S.threshold_sample(cells, plan, p["tau"])
            case "filter_threshold":
                out = S.filter_threshold(cells, plan, p["cut"], p["tau"])
            case "uniform":
                out = S.uniform_sample(cells, plan, p["fraction"])
            case "full":
                out = S.full_geometric(cells, plan).selectExpr("*", "CAST(value AS DOUBLE) AS weight")
            case _:
                out, meta["tau"] = S.priority_sample(cells, plan, p["s"], p.get("cut", 0) if self.how == "filter_priority" else 0, p.get("tau0"))
        return Released(out.select("cell_id", "value", "weight"), self.domain, meta)


def release(rows: DataFrame) -> ReleasePlan:
    return ReleasePlan(rows)


def suggest(m: int, n: float, total: float, eps: float, target: int, sensitivity: float = 1.0) -> dict[str, float]:
    """Parameters for about `target` rows, from public or noised totals."""
    alpha = alpha_of(eps, sensitivity)
    mean = total / max(n, 1)
    return {"cut": pick_cut(m, round(n), alpha, target), "tau": pick_tau(total, m, alpha, target), "combined_cut": advise_cut(mean, 0.2 * mean, n / m), "noise_sd": math.sqrt(moments(alpha)["variance"])}

