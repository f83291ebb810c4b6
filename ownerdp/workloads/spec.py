"""One description of a private query, from which come the Spark plan and, for checks against another engine, SQL text."""

from __future__ import annotations

import warnings
from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ownerdp.functions import aggregates as A
from ownerdp.functions.noise import CODES, NoNoise, TestNoise, draw_tag
from ownerdp.operators.threshold import owner_threshold
from ownerdp.params import PrivacyParams, default_delta
from ownerdp.plans.ownership import OwnedFrame
from ownerdp.plans.rewrite import private_aggregate
from ownerdp.sources.tables import read_table

SEED = 20
PLACES = 4
_MAKE = {"owners": lambda n, c, lo, hi: A.priv_count_owners(n), "count": lambda n, c, lo, hi: A.priv_count(n, c, lo, hi), "sum": A.priv_sum, "avg": A.priv_avg, "var": A.priv_var, "stddev": A.priv_stddev}


@dataclass(frozen=True)
class Release:
    """kind: owners, count, sum, avg, var or stddev; column: its name in the source, None for rows."""

    kind: str
    name: str
    column: str | None = None
    lo: float | None = None
    hi: float | None = None

    def agg(self):
        return _MAKE[self.kind](self.name, self.column, self.lo, self.hi)


@dataclass(frozen=True)
class Workload:
    """source: the owned relation in Spark; sql: the same relation as a SQL query with the owner's column ``o``.

    owners_of: a table with a row for each owner, from whose size delta follows; for experiments, where that size is public.
    """

    source: Callable[[SparkSession, str], OwnedFrame]
    sql: str
    keys: Sequence[str]
    releases: Sequence[Release]
    params: PrivacyParams
    noisy: bool = True
    domain: str | None = None
    leftovers: bool = False
    intervals: float | None = None
    options: dict = field(default_factory=dict)
    owners_of: str | None = None

    def params_for(self, spark: SparkSession, folder: str) -> PrivacyParams:
        if self.owners_of is None:
            return self.params
        with warnings.catch_warnings():
            warnings.simplefilter("ignore")  # the given tables have so few owners that no delta of this rule protects anyone
            return self.params.with_(delta=default_delta(read_table(spark, folder, self.owners_of).count(), self.params.eps))

    def noise(self):
        return TestNoise(SEED) if self.noisy else NoNoise(unsafe_for_tests=True, seed=SEED)

    def run(self, spark: SparkSession, folder: str) -> DataFrame:
        domain = None
        if self.domain is not None:
            domain = spark.sql(self.domain)
        result = private_aggregate(
            self.source(spark, folder), list(self.keys), [r.agg() for r in self.releases], self.params_for(spark, folder), self.noise(), key_domain=domain, leftovers=self.leftovers, intervals=self.intervals, **self.options
        )
        return rounded(result.df)

    def oracle(self) -> str:
        return _Oracle(self).text()


def rounded(df: DataFrame, places: int = PLACES) -> DataFrame:
    return df.select(*(F.round(F.col(f"`{f.name}`"), places).alias(f.name) if f.dataType.simpleString() == "double" else F.col(f"`{f.name}`") for f in df.schema))


# SQL of another engine, written from the formulas ----------------------------------------------------------------------


def sql_message(tag: str, keys: Sequence[str]) -> str:
    part = "CASE WHEN {k} IS NULL THEN 'N' ELSE 'V' || length(CAST({k} AS VARCHAR)) || ':' || CAST({k} AS VARCHAR) END"
    return " || ".join([f"'{SEED}|{tag}|'", *(part.format(k=k) for k in keys)])


def sql_uniform(tag: str, keys: Sequence[str]) -> str:
    return f"((('0x' || substr(md5({sql_message(tag, keys)}), 1, 13))::BIGINT + 0.5::DOUBLE) / {CODES}::DOUBLE)"


def sql_laplace(scale: float | str, tag: str, keys: Sequence[str], noisy: bool = True) -> str:
    if not noisy:
        return "0.0::DOUBLE"
    u = sql_uniform(tag, keys)
    return f"(-({scale!r})::DOUBLE * sign({u} - 0.5) * ln(1 - 2 * abs({u} - 0.5)))" if not isinstance(scale, str) else f"(-({scale}) * sign({u} - 0.5) * ln(1 - 2 * abs({u} - 0.5)))"


def sql_threshold(eps_t: float, eps: float, c_u: int, table: str) -> str:
    """The threshold with the default delta for the rows of a table of owners."""
    return f"(SELECT 1 - {c_u!r}::DOUBLE / {eps_t!r}::DOUBLE * ln(2 - 2 * pow(1 - exp(-{eps!r}::DOUBLE * pow(ln(count(*)::DOUBLE), 2)), 1.0::DOUBLE / {c_u})) FROM {table})"


def sql_clamp(x: str, lo: float, hi: float) -> str:
    return f"CASE WHEN ({x}) IS NULL THEN NULL WHEN isnan({x}) THEN greatest({lo!r}::DOUBLE, least({hi!r}::DOUBLE, 0)) ELSE greatest({lo!r}::DOUBLE, least({hi!r}::DOUBLE, {x})) END"


class _Oracle:
    def __init__(self, w: Workload):
        self.w = w
        has_keys = bool(w.keys)
        self.suppress = has_keys and w.domain is None and w.params.suppress
        self.c_u = w.params.c_u if has_keys else 1
        parts = len(w.releases) + self.suppress
        self.eps = w.params.eps / (self.c_u * parts)
        tau = w.params.tau
        if self.suppress and w.leftovers:
            self.eps = w.params.eps / (len(w.releases) * self.c_u + self.c_u + 1)
            tau = owner_threshold(self.eps * (self.c_u + 1), w.params.delta, self.c_u + 1) if tau is None else tau
        elif self.suppress and tau is None and w.owners_of is not None:
            tau = sql_threshold(self.eps * self.c_u, w.params.eps, self.c_u, w.owners_of)
        elif self.suppress and tau is None:
            tau = owner_threshold(self.eps * self.c_u, w.params.delta, self.c_u)
        self.tau = tau if isinstance(tau, str) else repr(tau)

    def partial(self, r: Release) -> str:
        x = r.column
        return {"owners": "count(*)", "count": f"count({x or '*'})", "sum": f"sum({x})"}.get(r.kind, f"avg({x}::DOUBLE)") + "::DOUBLE"

    def merged(self, r: Release) -> str:
        return f"{'avg' if r.kind in ('avg', 'var', 'stddev') else 'sum'}(p_{r.name})"

    def sums(self, r: Release) -> list[str]:
        p = f"p_{r.name}"
        if r.kind == "owners":
            return [f"count(*)::DOUBLE AS s_{r.name}"]
        if r.kind == "count" and r.lo is None:
            return [f"sum(CASE WHEN {p} > 0 THEN 1 ELSE 0 END)::DOUBLE AS s_{r.name}"]
        if r.kind in ("count", "sum"):
            return [f"coalesce(sum({sql_clamp(p, r.lo, r.hi)}), 0) AS s_{r.name}"]
        out = [f"coalesce(sum({sql_clamp(p, r.lo, r.hi)} - {(r.lo + r.hi) / 2!r}), 0) AS s_{r.name}", f"count({p})::DOUBLE AS n_{r.name}"]
        if r.kind != "avg":
            lo, hi = A.Var.squared_limits(r.lo, r.hi)
            c = f"({sql_clamp(p, r.lo, r.hi)})"
            out.append(f"coalesce(sum({sql_clamp(f'({c} * {c})', lo, hi)} - {(lo + hi) / 2!r}), 0) AS q_{r.name}")
        return out

    def _mean(self, r: Release, s: str, lo: float, hi: float, eps: float, part: str, keys) -> str:
        noisy = self.w.noisy
        total = f"({s} + {sql_laplace((hi - lo) / 2 / (eps / 2), draw_tag(r.name, part + 'sum'), keys, noisy)})"
        count = f"greatest(n_{r.name} + {sql_laplace(2 / eps, draw_tag(r.name, part + 'count'), keys, noisy)}, 1.0)"
        return sql_clamp(f"({(lo + hi) / 2!r} + {total} / {count})", lo, hi)

    def released(self, r: Release, keys: Sequence[str]) -> list[str]:
        e, noisy, out = self.eps, self.w.noisy, []
        if r.kind in ("owners", "count", "sum"):
            scale = 1 / e if r.lo is None else max(abs(r.lo), abs(r.hi)) / e
            value = f"s_{r.name} + {sql_laplace(scale, draw_tag(r.name), keys, noisy)}"
            if self.w.intervals is not None:
                width = r.agg().half_width(self.w.intervals, e, r.lo, r.hi)
                out = [f"round({value} - {width!r}, {PLACES}) AS {r.name}_lo", f"round({value} + {width!r}, {PLACES}) AS {r.name}_hi"]
        elif r.kind == "avg":
            value = self._mean(r, f"s_{r.name}", r.lo, r.hi, e, '', keys)
        else:
            lo, hi = A.Var.squared_limits(r.lo, r.hi)
            first = self._mean(r, f"s_{r.name}", r.lo, r.hi, e / 2, '', keys)
            second = self._mean(r, f"q_{r.name}", lo, hi, e / 2, 'squares_', keys)
            value = f"greatest(0, ({second}) - ({first}) * ({first}))"
            if r.kind == "stddev":
                value = f"sqrt({value})"
        return [f"round({value}, {PLACES}) AS {r.name}", *out]

    def text(self) -> str:
        w, keys = self.w, list(self.w.keys)
        listed = "".join(f"{k}, " for k in keys)
        group = f"GROUP BY {', '.join(keys)}" if keys else ""
        partials = ", ".join(f"{self.partial(r)} AS p_{r.name}" for r in w.releases)
        within = f" WHERE ({', '.join(keys)}) IN (SELECT {', '.join(keys)} FROM ({w.domain}))" if w.domain else ""
        ctes = [f"src AS ({w.sql})", f"part AS (SELECT o, {listed}{partials} FROM src{within} GROUP BY o{''.join(f', {k}' for k in keys)})"]
        if keys:
            ctes.append(f"lim AS (SELECT * FROM part QUALIFY row_number() OVER (PARTITION BY o ORDER BY md5({sql_message('limit', ['o', *keys])})) <= {self.c_u})")
        else:
            ctes.append("lim AS (FROM part)")
        sums = ", ".join(s for r in w.releases for s in self.sums(r))
        ctes.append(f"tot AS (SELECT {listed}count(*) AS owners, {sums} FROM lim {group})")
        source = "tot"
        if w.domain:
            names = [s.rsplit(" AS ", 1)[1] for r in w.releases for s in self.sums(r)]
            ctes.append(f"listed AS (SELECT {listed}{', '.join(f'coalesce({n}, 0) AS {n}' for n in names)} FROM (SELECT DISTINCT {', '.join(keys)} FROM ({w.domain})) LEFT JOIN tot USING ({', '.join(keys)}))")
            source = "listed"
        out = ", ".join(x for r in w.releases for x in self.released(r, keys))
        where = f" WHERE owners + {sql_laplace(1 / self.eps, draw_tag('', 'owners'), keys, w.noisy)} >= {self.tau}" if self.suppress else ""
        body = f"SELECT {listed}{out} FROM {source}{where}"
        if not (self.suppress and w.leftovers):
            return f"WITH {', '.join(ctes)} {body}"
        ctes.append(f"kept AS ({body})")
        ctes.append(f"rest AS (SELECT o, {', '.join(f'{self.merged(r)} AS p_{r.name}' for r in w.releases)} FROM lim ANTI JOIN kept USING ({', '.join(keys)}) GROUP BY o)")
        ctes.append(f"rest_tot AS (SELECT count(*) AS owners, {sums} FROM rest)")
        last = ", ".join(x for r in w.releases for x in self.released(r, []))
        return (
            f"WITH {', '.join(ctes)} SELECT *, false AS is_leftover FROM kept UNION ALL BY NAME SELECT {''.join(f'NULL AS {k}, ' for k in keys)}{last}, true AS is_leftover FROM rest_tot"
            f" WHERE owners + {sql_laplace(1 / self.eps, draw_tag('', 'owners of leftovers'), [], w.noisy)} >= {self.tau}"
        )
