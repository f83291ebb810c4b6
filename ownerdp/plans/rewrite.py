"""The private aggregation: two aggregations, a limit on each owner's partitions between them, noise, and a threshold on keys."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ownerdp.functions.aggregates import Agg, Context, Quantile
from ownerdp.functions.noise import Noise, draw_tag
from ownerdp.ledger import PrivacyLedger
from ownerdp.operators.bounds import approx_bounds
from ownerdp.operators.quantile import bisect
from ownerdp.operators.sampling import limit_partitions
from ownerdp.operators.threshold import owner_threshold, suppress_rare_keys
from ownerdp.params import PrivacyParams, Shares
from ownerdp.plans.ownership import OwnedFrame, OwnershipError, is_public, validate_ownership
from ownerdp.result import PrivateResult
from ownerdp.sources.tables import materialise

OWNERS = "__owners"
NOISY_OWNERS = "__noisy_owners"


def _named(keys: Sequence[str | Column]) -> tuple[list[Column], list[str]]:
    """The columns of the grouping and their names; expressions need an alias."""
    names = [k if isinstance(k, str) else _alias_of(k) for k in keys]
    if None in names:
        raise ValueError("give each key expression an alias")
    return [F.col(k) if isinstance(k, str) else k for k in keys], names


def _alias_of(column: Column) -> str | None:
    text = str(column)  # Column<'... AS name'>
    inner = text[text.find("'") + 1 : text.rfind("'")]
    return inner.rsplit(" AS ", 1)[1].strip("`") if " AS " in inner else None


def partials(owned: OwnedFrame, keys: Sequence[str | Column], aggs: Sequence[Agg], strategy: str = "combine") -> DataFrame:
    """One row for each owner and partition, whatever the number of its rows.

    ``combine`` adds up on the map side before the shuffle by (owner, keys); ``copartition`` shuffles the rows by owner once, which
    the limit on partitions then uses too: better if an owner has about one row in each partition.
    """
    df = owned.unowned()
    if strategy == "copartition":
        df = df.repartition(owned.owner)
    columns, names = _named(keys)
    grouping = [c.alias(n) if not isinstance(k, str) else c for k, c, n in zip(keys, columns, names, strict=True)]
    return df.groupBy(F.col(owned.owner).alias("__owner"), *grouping).agg(*(a.partial().alias(a.p) for a in aggs), F.lit(1).alias("__present"))


def cross_owner(bounded: DataFrame, keys: Sequence[str], aggs: Sequence[Agg], limits: dict[str, tuple] | None = None) -> DataFrame:
    """Sums over owners for each partition, clamped, with the exact number of owners in ``__owners``."""
    limits = limits or {}
    sums = {}
    for a in aggs:
        if not isinstance(a, Quantile):
            sums |= a.combine(*limits.get(a.name, (a.lo, a.hi)))
    return bounded.groupBy(*keys).agg(F.count("__owner").alias(OWNERS), *(c.alias(n) for n, c in sums.items()))


def _limits(bounded: DataFrame, aggs: Sequence[Agg], shares: Shares, c_u: int, noise: Noise, p: float) -> tuple[dict[str, tuple], dict[str, Column]]:
    """Limits of each automatic aggregate over all partitions together: a few numbers, read by the driver after noise, in one job."""
    automatic, rows = [a for a in aggs if a.automatic], None
    for i, a in enumerate(automatic):
        row = approx_bounds(bounded, [], a.p, shares.per_aggregate * c_u / 2, noise, p, a.bounds_kind, c_u, tag=draw_tag(a.name, "bounds")).withColumn("i", F.lit(i))
        rows = row if rows is None else rows.unionByName(row)
    by_number = {r["i"]: r for r in rows.collect()} if rows is not None else {}
    found, outside = {}, {}
    for i, a in enumerate(automatic):
        row = by_number.get(i)
        found[a.name] = (None, None) if row is None or row["lower"] is None else (float(row["lower"]), float(row["upper"]))
        outside[a.name] = F.lit(None if row is None else row["outside"]).cast("double")
    return found, outside


def checked_tables(owned: OwnedFrame, keys: Sequence[str | Column], aggs: Sequence[Agg]) -> set[str]:
    """Raises OwnershipError unless the rows, the keys and what the aggregates read each come from one owner; the names of the private tables."""
    columns, _ = _named(keys)
    arguments = [F.col(a.col) if isinstance(a.col, str) else a.col for a in aggs if a.col is not None]
    read = [c.alias(f"__read_{i}") for i, c in enumerate([*columns, *arguments])]
    return validate_ownership(owned.unowned().select(F.col(f"`{owned.owner}`"), *read), owned.owner)


def private_aggregate(
    owned: OwnedFrame, keys: Sequence[str | Column], aggs: Sequence[Agg], params: PrivacyParams, noise: Noise, key_domain: DataFrame | None = None,
    leftovers: bool = False, intervals: float | None = None, rounded: bool = False, strategy: str = "combine", sampler: str = "window", bounds_p: float = 1 - 1e-9,
    ledger: PrivacyLedger | None = None, query: str = "", label: str | None = None,
) -> PrivateResult:
    """A noisy row for each key that enough owners share.

    keys: columns of the grouping, none for one row over everything. key_domain: a public list of keys, each of which is
    released, absent ones as noise, and no other. leftovers: one more row for the owners of suppressed keys. intervals:
    adds ``<name>_lo`` and ``<name>_hi``, which hold the result without noise with this probability. ledger: charged before
    anything runs, for each private table that is read. label: names a release that may be made again with the same noise; without
    one, every call draws anew.

    The analysed plan of all that is read is checked first: OwnershipError if any operator or subquery may mix owners.
    """
    _, names = _named(keys)
    if len({*names, *(a.name for a in aggs)}) < len(names) + len(aggs):
        raise ValueError("names of keys and aggregates must differ")
    tables = checked_tables(owned, keys, aggs)
    if key_domain is not None and not is_public(key_domain):
        raise OwnershipError("the list of keys comes from private rows; list keys that are public, or a result that was written (fixed)")
    has_keys, suppress = bool(names), bool(names) and key_domain is None and params.suppress
    c_u = params.c_u if has_keys else 1
    shares = params.split(len(aggs), needs_count=suppress, has_keys=has_keys)
    if suppress and leftovers:
        # an owner's suppressed partitions become one row, so aggregates still see c_u of it, but its presence is counted once more
        each = params.eps / (len(aggs) * c_u + c_u + 1)
        shares = Shares(each, each, each * (c_u + 1))
        if params.tau is None:
            params = params.with_(tau=owner_threshold(shares.count_of_query, params.delta, c_u + 1))
    if ledger is not None:
        for table in sorted(tables) or [""]:
            ledger.charge(table, owned.owner, params.eps, params.delta if suppress else 0.0, query, PrivacyLedger.plan_hash(owned.unowned()))
    noise = noise.for_release(label)

    df = partials(owned, keys, aggs, strategy)
    if key_domain is not None:  # before the limit, so that no partition outside the list uses it up
        same = [df[n].eqNullSafe(key_domain[n]) for n in names]
        df = df.join(key_domain.select(*names).distinct(), same, "left_semi")
    bounded = limit_partitions(df, "__owner", c_u, noise, names, sampler) if has_keys else df
    if any(a.automatic for a in aggs) or leftovers or any(isinstance(a, Quantile) for a in aggs):
        bounded = materialise(bounded, "bounded")  # read more than once, and every reader must see the same sample
    limits, outside = _limits(bounded, aggs, shares, c_u, noise, bounds_p)
    released = _release(bounded, names, aggs, shares, params, noise, limits, outside, suppress, c_u, key_domain, intervals, rounded)
    if suppress and leftovers:
        rest = bounded.join(released.select(*names), [bounded[n].eqNullSafe(released[n]) for n in names], "left_anti")
        one_row = rest.groupBy("__owner").agg(*(_merged(a).alias(a.p) for a in aggs), F.lit(1).alias("__present"))
        row = _release(one_row, [], aggs, shares, params, noise, limits, outside, True, 1, None, intervals, rounded, of=" of leftovers")
        kinds = {f.name: f.dataType for f in released.schema}
        released = released.withColumn("is_leftover", F.lit(False)).unionByName(row.select(*(F.lit(None).cast(kinds[n]).alias(n) for n in names), *row.columns).withColumn("is_leftover", F.lit(True)))
    return PrivateResult(released, names, list(aggs), params, noise)


def _merged(a: Agg) -> Column:
    """One value for all suppressed partitions of an owner."""
    return F.avg(a.p) if a.partial.__func__.__qualname__.startswith(("Avg", "Var", "Quantile")) else F.sum(a.p)


def _release(bounded, names, aggs, shares, params, noise, limits, outside, suppress, c_u, key_domain, intervals, rounded, of="") -> DataFrame:
    usable = [a for a in aggs if limits.get(a.name, (0, 0))[0] is not None]
    totals = cross_owner(bounded, names, usable, limits)
    if key_domain is not None:
        found = totals.select(*(F.col(n).alias(f"__k_{n}") for n in names), *(c for c in totals.columns if c not in names))
        listed = key_domain.select(*names).distinct()
        totals = listed.join(found, [listed[n].eqNullSafe(found[f"__k_{n}"]) for n in names], "left").drop(*(f"__k_{n}" for n in names))
        totals = totals.fillna(0, subset=[c for c in totals.columns if c not in names])
    totals = noise.prepare(totals)
    key_columns = [F.col(n) for n in names]
    out: dict[str, Column] = {}
    for a in aggs:
        lo, hi = limits.get(a.name, (a.lo, a.hi))
        eps = shares.per_aggregate / 2 if a.automatic else shares.per_aggregate
        if a not in usable:
            out[a.name] = F.lit(None).cast("double")
            continue
        if not isinstance(a, Quantile):
            context = Context(noise, key_columns, eps, rounded)
            out[a.name] = a.release(context, lo, hi)
            if intervals is not None:
                out |= _interval(a, context, intervals, lo, hi)
        if a.automatic:
            out[f"{a.name}_outside"] = outside[a.name]
    if suppress:
        count = F.col(OWNERS) + noise.laplace(1 / shares.per_count, draw_tag("", f"owners{of}"), key_columns)  # aggregates have names, so none shares this draw
        tau = params.tau if params.tau is not None else owner_threshold(shares.count_of_query, params.delta, c_u)
        totals = suppress_rare_keys(totals.withColumn(NOISY_OWNERS, count), NOISY_OWNERS, tau)
    public_keys = [F.col(n).alias(n, metadata={"released": True}) for n in names]  # an owner among the keys is one no more
    released = totals.select(*public_keys, *(c.alias(n) for n, c in out.items()), *([noise.NONCE] if hasattr(noise, "NONCE") else []))
    released = noise.finish(released)
    for a in aggs:
        if isinstance(a, Quantile) and a in usable:
            lo, hi = limits.get(a.name, (a.lo, a.hi))
            eps = shares.per_aggregate / 2 if a.automatic else shares.per_aggregate
            found = bisect(bounded, names, a.p, a.name, draw_tag(a.name, "search"), a.q, lo, hi, a.depth, eps, noise, a.extra.get("array", False))
            if not names:
                released = _beside(released, found)
            else:
                keyed = found.select(*(F.col(n).alias(f"__k_{n}") for n in names), a.name)
                released = released.join(keyed, [released[n].eqNullSafe(keyed[f"__k_{n}"]) for n in names], "left").drop(*(f"__k_{n}" for n in names))
    order = [c for a in aggs for c in (a.name, f"{a.name}_lo", f"{a.name}_hi", f"{a.name}_outside")]
    return released.select(*names, *(c for c in order if c in released.columns))


def _beside(one: DataFrame, other: DataFrame) -> DataFrame:
    """Two results of one row each, side by side."""
    return one.withColumn("__one", F.lit(1)).join(other.withColumn("__one", F.lit(1)), "__one", "left").drop("__one")


def _interval(a: Agg, c: Context, level: float, lo: float, hi: float) -> dict[str, Column]:
    try:
        low, high = a.interval(c, level, lo, hi)
    except NotImplementedError:
        return {}
    return {f"{a.name}_lo": low, f"{a.name}_hi": high}
