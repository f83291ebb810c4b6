"""Laplace noise as columns.

Noise is a keyed function of what is released: the secret of the release, the tag of the draw and the encoded keys. A retried task, a second
action and a speculative copy all get the same noise, so nothing can be averaged out.
"""

from __future__ import annotations

import hashlib
import math
import secrets
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ownerdp.sources.tables import materialise

HEX_DIGITS, CODES = 13, 1 << 52


def encode_keys(keys: Sequence[Column]) -> Column:
    """One string for a list of keys, different for different lists: each value behind its length, NULL marked as such."""
    parts = [F.coalesce(F.concat(F.lit("V"), F.length(k.cast("string")).cast("string"), F.lit(":"), k.cast("string")), F.lit("N")) for k in keys]
    return F.concat(*parts) if parts else F.lit("")


def draw_tag(name: str, part: str = "value") -> str:
    """What tells one draw of a release from all others: no two pairs of a name and a part give the same text, whatever the name holds."""
    return f"{len(name)}:{name}/{part}"


class Noise:
    """A source of noise. ``hex_digest`` gives a string of hex digits for a message."""

    exact = False

    def for_release(self, label: str | None = None) -> Noise:
        """The noise of one release, which no other release shares. ``label`` names a release that may have to be made again, as it was."""
        return self

    def hex_digest(self, message: Column) -> Column:
        raise NotImplementedError

    def prepare(self, df: DataFrame) -> DataFrame:
        """Called once on the rows that are released, before any noise is drawn."""
        return df

    def finish(self, df: DataFrame) -> DataFrame:
        return df

    def message(self, tag: str | Column, keys: Sequence[Column]) -> Column:
        lead = tag if isinstance(tag, Column) else F.lit(tag)
        return F.concat(lead, F.lit("|"), encode_keys(keys))

    def order(self, tag: str, keys: Sequence[Column]) -> Column:
        """A string by which rows stand in a random order."""
        return self.hex_digest(self.message(tag, keys))

    def uniform(self, tag: str | Column, keys: Sequence[Column]) -> Column:
        """A number in (0, 1), never at an end."""
        whole = F.conv(F.substring(self.hex_digest(self.message(tag, keys)), 1, HEX_DIGITS), 16, 10).cast("long")
        return (whole + F.lit(0.5)) / F.lit(float(CODES))

    def laplace(self, scale, tag: str | Column, keys: Sequence[Column]) -> Column:
        """Zero-mean Laplace noise by the inverse of its distribution function. scale: a number or a column."""
        x = self.uniform(tag, keys) - F.lit(0.5)
        b = scale if isinstance(scale, Column) else F.lit(float(scale))
        return -b * F.signum(x) * F.log(1 - 2 * F.abs(x))

    def draw(self, scale: float, message: str) -> float:
        """The same noise in Python, for iterative methods inside a task."""
        raise NotImplementedError


def _from_hex(digits: str, scale: float) -> float:
    x = (int(digits[:HEX_DIGITS], 16) + 0.5) / CODES - 0.5
    return -scale * math.copysign(1, x) * math.log(1 - 2 * abs(x))


class KeyedNoise(Noise):
    """For releases: SHA-256 under a fresh secret of 256 bits, from which each release derives one of its own. Redact the secret in logs (spark.redaction.string.regex)."""

    def __init__(self, secret: str | None = None):
        self.secret = secret or secrets.token_hex(32)

    def for_release(self, label: str | None = None) -> KeyedNoise:
        own = f"labelled|{label}" if label is not None else f"fresh|{secrets.token_hex(32)}"
        return KeyedNoise(hashlib.sha256(f"{self.secret}|release|{own}".encode()).hexdigest())

    def hex_digest(self, message: Column) -> Column:
        return F.sha2(F.concat(F.lit(self.secret + "|"), message), 256)

    def draw(self, scale: float, message: str) -> float:
        return _from_hex(hashlib.sha256(f"{self.secret}|{message}".encode()).hexdigest(), scale)


class TestNoise(Noise):
    """Reproducible noise from MD5 and a seed, the same in every release, which other engines can compute as well. Protects nothing."""

    __test__ = False

    def __init__(self, seed: int = 0):
        self.seed = seed

    def hex_digest(self, message: Column) -> Column:
        return F.md5(F.concat(F.lit(f"{self.seed}|"), message))

    def draw(self, scale: float, message: str) -> float:
        return _from_hex(hashlib.md5(f"{self.seed}|{message}".encode()).hexdigest(), scale)


class RunNoise(Noise):
    """Fast and reproducible, for measuring over millions of draws. Protects nothing; no other engine computes it."""

    def __init__(self, seed: int = 0):
        self.seed = seed

    def uniform(self, tag: str | Column, keys: Sequence[Column]) -> Column:
        lead = tag if isinstance(tag, Column) else F.lit(tag)
        return (F.shiftrightunsigned(F.xxhash64(F.lit(self.seed), lead, *keys), 11).cast("double") + F.lit(0.5)) / F.lit(2.0**53)

    def order(self, tag: str, keys: Sequence[Column]) -> Column:
        return F.hex(F.xxhash64(F.lit(self.seed), F.lit(tag), *keys))

    def draw(self, scale: float, message: str) -> float:
        return _from_hex(hashlib.blake2b(f"{self.seed}|{message}".encode(), digest_size=8).hexdigest(), scale)


class EntropyNoise(Noise):
    """The operating system's entropy, one nonce for each released row; the result is written before anyone sees it."""

    NONCE = "__nonce"

    def prepare(self, df: DataFrame) -> DataFrame:
        kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema)

        def nonces(batches):
            for batch in batches:
                yield batch.assign(**{EntropyNoise.NONCE: [secrets.token_hex(32) for _ in range(len(batch))]})

        return materialise(df.mapInPandas(nonces, f"{kinds}, {self.NONCE} string"), "entropy")

    def hex_digest(self, message: Column) -> Column:
        return F.sha2(F.concat(F.col(self.NONCE), F.lit("|"), message), 256)

    def order(self, tag: str, keys: Sequence[Column]) -> Column:
        return F.sha2(F.concat(F.lit(self._order_secret), self.message(tag, keys)), 256)

    def __init__(self):
        self._order_secret = secrets.token_hex(32)

    def for_release(self, label: str | None = None) -> EntropyNoise:
        return EntropyNoise()

    def finish(self, df: DataFrame) -> DataFrame:
        return materialise(df.drop(self.NONCE), "release")

    def draw(self, scale: float, message: str) -> float:
        return _from_hex(secrets.token_hex(16), scale)


class NoNoise(Noise):
    """Exact bounded answers, for tests only; sampling stays as with TestNoise."""

    exact = True

    def __init__(self, unsafe_for_tests: bool = False, seed: int = 0):
        if not unsafe_for_tests:
            raise ValueError("NoNoise releases exact values; pass unsafe_for_tests=True")
        self.seed = seed

    def hex_digest(self, message: Column) -> Column:
        return F.md5(F.concat(F.lit(f"{self.seed}|"), message))

    def laplace(self, scale, tag, keys) -> Column:
        return F.lit(0.0)

    def draw(self, scale: float, message: str) -> float:
        return 0.0


def rounding_step(scale: float) -> float:
    """The smallest power of two above the scale."""
    return 2.0 ** (math.floor(math.log2(scale)) + 1)


def round_to_step(value: Column, scale: float) -> Column:
    """The value as a multiple of the step, so that the low bits of a double tell nothing."""
    step = rounding_step(scale)
    return F.round(value / F.lit(step)) * F.lit(step)
