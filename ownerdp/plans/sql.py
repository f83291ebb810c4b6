"""Private aggregation in SQL text.

    SELECT key, ..., priv_sum(value, 0, 10) AS total FROM relation [WHERE ...] [GROUP BY key, ...] [WITH PRIVACY (eps 1, delta 1e-6, partitions 3)]

A key is a column, or an expression with a name, by which, by whose text or by whose place it is grouped. The clause may also ask for
``intervals 0.95``, ``leftovers`` and ``rounded``. The relation may be any SQL that keeps each row with one owner, subqueries in parentheses included; it is analysed by Spark
and checked operator by operator.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from ownerdp.functions import aggregates as A
from ownerdp.functions.noise import KeyedNoise, Noise
from ownerdp.params import PrivacyParams
from ownerdp.plans.ownership import OwnedFrame, OwnershipError, owner_column, validate_ownership
from ownerdp.plans.rewrite import private_aggregate
from ownerdp.result import PrivateResult

_CLAUSE = re.compile(r"\bWITH\s+PRIVACY\s*\(([^()]*)\)\s*;?\s*$", re.I)
_CALL = re.compile(r"^\s*(priv_\w+)\s*\((.*)\)\s+AS\s+`?(\w+)`?\s*$", re.I | re.S)
_OPTIONS = {"intervals": float, "leftovers": lambda _: True, "rounded": lambda _: True}
_NAMED = re.compile(r"^(.*\S)\s+AS\s+`?(\w+)`?$", re.I | re.S)
_SETTINGS = {"eps": "eps", "epsilon": "eps", "delta": "delta", "partitions": "c_u", "threshold": "tau"}


def _split(text: str, at: str = ",") -> list[str]:
    """Parts between separators that stand outside parentheses and quotes."""
    parts, depth, quote, begin = [], 0, "", 0
    for i, c in enumerate(text):
        if quote:
            quote = "" if c == quote else quote
        elif c in "'\"`":
            quote = c
        else:
            depth += (c == "(") - (c == ")")
            if depth == 0 and c == at:
                parts.append(text[begin:i])
                begin = i + 1
    return [p.strip() for p in [*parts, text[begin:]] if p.strip()]


def _outside(text: str, word: str) -> int:
    """Where a keyword stands outside parentheses and quotes; -1 if nowhere."""
    depth, quote = 0, ""
    for m in re.finditer(r"['\"`()]|\b\w+(?:\s+BY)?\b", text, re.I):
        t = m[0]
        if quote:
            quote = "" if t == quote else quote
        elif t in "'\"`":
            quote = t
        elif t in "()":
            depth += 1 if t == "(" else -1
        elif depth == 0 and re.fullmatch(word, t, re.I):
            return m.start()
    return -1


def _call(name: str, function: str, arguments: list[str]) -> A.Agg:
    function = function.lower()
    expression = lambda i: F.expr(arguments[i])
    limits = lambda i: (float(arguments[i]), float(arguments[i + 1])) if len(arguments) > i + 1 else (None, None)
    if function == "priv_count_owners":
        return A.priv_count_owners(name)
    if function == "priv_count":
        if not arguments or arguments == ["*"]:
            return A.priv_count(name)
        if arguments[0] == "*":
            return A.priv_count(name, None, *limits(1))
        return A.priv_count(name, expression(0), *limits(1))
    if function in ("priv_quantile", "priv_ntile"):
        of = float(arguments[1])
        return getattr(A, function)(name, expression(0), of if function == "priv_quantile" else int(of), *limits(2))
    if function in ("priv_sum", "priv_avg", "priv_var", "priv_stddev", "priv_median", "priv_min", "priv_max"):
        return getattr(A, function)(name, expression(0), *limits(1))
    raise OwnershipError(f"{function} is no private function")


def _clause(text: str) -> dict:
    settings = {}
    for part in _split(text):
        key, *value = part.replace("=", " ").lower().split()
        if key in _OPTIONS and len(value) <= 1:
            settings[key] = _OPTIONS[key](*(value or [None]))
        elif key in _SETTINGS and len(value) == 1:
            settings[_SETTINGS[key]] = int(value[0]) if key == "partitions" else float(value[0])
        else:
            raise OwnershipError(f"{part} is no setting of privacy")
    return settings


def parse_private(text: str) -> tuple[list[str | Column], list[A.Agg], str, dict]:
    """(keys, aggregates, SQL of the relation, settings)."""
    settings = {}
    if m := _CLAUSE.search(text):
        settings, text = _clause(m[1]), text[: m.start()]
    text = text.strip().rstrip(";")
    m = re.match(r"SELECT\s+", text, re.I)
    start, by = _outside(text, "FROM"), _outside(text, r"GROUP\s+BY")
    if not m or start < 0:
        raise OwnershipError("expected SELECT ... FROM ...")
    for word in ("HAVING", r"ORDER\s+BY", "LIMIT", "UNION"):
        if _outside(text, word) >= 0:
            raise OwnershipError("sort, filter and combine the result, not the private query")
    relation = text[start : by if by >= 0 else len(text)].strip()
    keys = _split(re.sub(r"^GROUP\s+BY\s+", "", text[by:], flags=re.I)) if by >= 0 else []
    aggs, plain, grouped = [], [], set()
    for place, item in enumerate(_split(text[m.end() : start]), 1):
        if call := _CALL.match(item):
            aggs.append(_call(call[3], call[1], _split(call[2])))
            continue
        named = _NAMED.match(item)
        names = {str(place), item.strip("`")} if named is None else {str(place), named[1], named[2]}
        used = {k for k in keys if k.strip("`") in names}
        if len(used) != 1:
            raise OwnershipError(f"group by {item}, once")
        grouped |= used
        plain.append(item.strip("`") if named is None else F.expr(named[1]).alias(named[2]))
    if grouped != set(keys):
        raise OwnershipError("each key must be selected")
    return plain, aggs, f"SELECT * {relation}", settings


def private_sql(spark: SparkSession, text: str, params: PrivacyParams | None = None, noise: Noise | None = None, **options) -> PrivateResult:
    """Runs a private query over views that ``OwnerCatalog.create_views`` made. A privacy clause in the text replaces the parameters' values."""
    keys, aggs, relation, settings = parse_private(text)
    if params is None and "eps" not in settings:
        raise ValueError("no privacy parameters")
    options = {k: settings.pop(k) for k in _OPTIONS if k in settings} | options
    params = params.with_(**settings) if params is not None else PrivacyParams(**settings)
    df = spark.sql(relation)
    validate_ownership(df)
    return private_aggregate(OwnedFrame.of(df, owner_column(df)), keys, aggs, params, noise or KeyedNoise(), **options)
