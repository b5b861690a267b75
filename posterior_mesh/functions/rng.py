"""Random numbers that depend on nothing but their key, so a retried or repartitioned task draws the same."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def uniform_of(*keys: Column | str | int, seed: int = 42) -> Column:
    """Uniform on (0, 1): 52 bits of the key's digest, plus a half."""
    parts = [k if isinstance(k, Column) else F.col(k) if isinstance(k, str) else F.lit(k) for k in keys]
    text = F.concat_ws("|", F.lit(str(seed)), *[p.cast("string") for p in parts])
    return (F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long") + 0.5) / float(1 << 52)


def normal_of(*keys: Column | str | int, seed: int = 42) -> Column:
    """Standard normal by the cosine half of two uniforms."""
    u, v = uniform_of(F.lit("a"), *keys, seed=seed), uniform_of(F.lit("b"), *keys, seed=seed)
    return F.sqrt(-2 * F.ln(u)) * F.cos(2 * F.pi() * v)


def uniform_sql(*keys: str, seed: int = 42) -> str:
    """The same for DuckDB."""
    text = " || '|' || ".join([f"'{seed}'", *(f"CAST({k} AS VARCHAR)" for k in keys)])
    return f"((CAST('0x' || substr(md5({text}), 1, 13) AS BIGINT) + 0.5) / 4503599627370496.0)"


def normal_sql(*keys: str, seed: int = 42) -> str:
    return f"(sqrt(-2 * ln({uniform_sql(chr(39) + 'a' + chr(39), *keys, seed=seed)})) * cos(2 * pi() * {uniform_sql(chr(39) + 'b' + chr(39), *keys, seed=seed)}))"


#: Tries of a Gamma draw. One is refused with a chance under 0.05, so all of them are with one under 4e-11; the draw is null then and is refused.
TRIES = 8


def gamma_of(shape: Column, *keys: Column | str | int, seed: int = 42) -> Column:
    """Gamma of scale 1, by squeezing a cubed normal; each try has keys of its own. Shapes under 1 take a draw of one more, times a power of a uniform.

    Tries are a fold that stops to compute once one fits, so that the expression holds the code of a single try.
    """
    d = F.when(shape < 1, shape + 1).otherwise(shape) - 1 / 3

    def fitting(t: Column) -> Column:
        root = 1 + t["z"] / F.sqrt(9 * d)
        v = root * root * root
        return F.when((root > 0) & (F.ln(t["u"]) < t["z"] * t["z"] / 2 + d - d * v + d * F.ln(F.greatest(v, F.lit(1e-300)))), d * v)

    def tried(k: Column) -> Column:
        name = F.concat(F.lit("g"), k.cast("string"))
        drawn = F.struct(normal_of(*keys, name, seed=seed).alias("z"), uniform_of(F.lit("c"), *keys, name, seed=seed).alias("u"))
        return F.element_at(F.transform(F.array(drawn), fitting), 1)

    first = F.sequence(F.lit(1), F.lit(TRIES))
    whole = F.aggregate(first, F.lit(None).cast("double"), lambda got, k: F.coalesce(got, tried(k)))
    whole = F.coalesce(whole, F.raise_error(F.lit("no try of a Gamma draw fitted: take another seed")).cast("double"))
    return F.when(shape <= 0, F.raise_error(F.lit("a Gamma shape is over 0")).cast("double")).when(shape < 1, whole * F.pow(uniform_of(F.lit("p"), *keys, seed=seed), 1 / shape)).otherwise(whole)


def beta_of(a: Column, b: Column, *keys: Column | str | int, seed: int = 42) -> Column:
    """Beta of two shapes: the share of the first of two Gamma draws."""
    x, y = gamma_of(a, *keys, F.lit("x"), seed=seed), gamma_of(b, *keys, F.lit("y"), seed=seed)
    return x / (x + y)


def gamma_sql(shape: str, *keys: str, seed: int = 42) -> str:
    """The same for DuckDB; ``shape`` is an SQL expression."""
    d = f"((CASE WHEN {shape} < 1 THEN {shape} + 1 ELSE {shape} END) - {1 / 3!r})"
    whens = []
    for k in range(1, TRIES + 1):
        z = normal_sql(*keys, f"'g{k}'", seed=seed)
        v = f"pow(1 + {z} / sqrt(9 * {d}), 3)"
        whens.append(f"WHEN {v} > 0 AND ln({uniform_sql(chr(39) + 'c' + chr(39), *keys, f'{chr(39)}g{k}{chr(39)}', seed=seed)}) < {z} * {z} / 2 + {d} - {d} * {v} + {d} * ln(greatest({v}, 1e-300)) THEN {d} * {v}")
    power = f"pow({uniform_sql(chr(39) + 'p' + chr(39), *keys, seed=seed)}, 1.0 / {shape})"
    return f"((CASE {' '.join(whens)} END) * (CASE WHEN {shape} < 1 THEN {power} ELSE 1 END))"
