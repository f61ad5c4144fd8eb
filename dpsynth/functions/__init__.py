"""SQL expressions: cell numbers, and noise from hashes for reproducible tests (never a release)."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from dpsynth.domain import DomainSpec


def cell_sql(spec: DomainSpec, subset: Sequence[int]) -> str:
    """Text of a subset's cell number, mixed radix over its codes; reads in Spark and DuckDB."""
    return " + ".join(f"cast({spec.attrs[i].name} as bigint) * {w}" for i, w in zip(subset, spec.strides(subset), strict=True))


def cell(spec: DomainSpec, subset: Sequence[int]) -> Column:
    return F.expr(cell_sql(spec, subset))


def uncell_sql(spec: DomainSpec, subset: Sequence[int], at: int, column: str = "cell") -> str:
    """Text of one code in a cell number."""
    weight = spec.strides(subset)[list(subset).index(at)]
    return f"cast(floor({column} / {weight}) as bigint) % {spec.attrs[at].size}"


def uniform(seed: int, *key: Column, salt: str = "u") -> Column:
    """In (0, 1), from the first twelve hex digits of an MD5 over seed and key."""
    text = F.concat_ws("|", F.lit(str(seed)), *[k.cast("string") for k in key], F.lit(salt))
    return (F.conv(F.substring(F.md5(text), 1, 12), 16, 10).cast("double") + 0.5) / float(1 << 48)


def gauss(seed: int, *key: Column) -> Column:
    return F.sqrt(-2 * F.ln(uniform(seed, *key))) * F.cos(2 * F.pi() * uniform(seed, *key, salt="v"))


def gumbel(seed: int, *key: Column) -> Column:
    return -F.ln(-F.ln(uniform(seed, *key)))


def laplace(seed: int, *key: Column) -> Column:
    u = uniform(seed, *key) - 0.5
    return -F.sign(u) * F.ln(1 - 2 * F.abs(u))


def uniform_duck(seed: int, *key: str, salt: str = "u") -> str:
    text = " || '|' || ".join([f"'{seed}'", *(f"cast({k} as varchar)" for k in key), f"'{salt}'"])
    return f"((('0x' || substr(md5({text}), 1, 12))::bigint + 0.5) / {float(1 << 48)!r})"


def gauss_duck(seed: int, *key: str) -> str:
    return f"(sqrt(-2 * ln({uniform_duck(seed, *key)})) * cos(2 * pi() * {uniform_duck(seed, *key, salt='v')}))"


def gumbel_duck(seed: int, *key: str) -> str:
    return f"(-ln(-ln({uniform_duck(seed, *key)})))"


def laplace_duck(seed: int, *key: str) -> str:
    u = f"({uniform_duck(seed, *key)} - 0.5)"
    return f"(-sign({u}) * ln(1 - 2 * abs({u})))"


#: name -> (parameters, body): SQL functions without Python in them.
SQL_FUNCTIONS = {
    "dp_uniform": ("seed string, k string", "return (cast(conv(substring(md5(concat_ws('|', seed, k, 'u')), 1, 12), 16, 10) as double) + 0.5) / 281474976710656.0D"),
    "dp_expected_l1": ("sigma double, cells bigint", "return sqrt(2 / pi()) * sigma * cells"),
    "dp_rho_gauss": ("sigma double", "return 1 / (2 * sigma * sigma)"),
    "dp_rho_exp": ("eps double", "return eps * eps / 8"),
}


def register(spark: SparkSession) -> None:
    """Make the functions above known to SQL in this session."""
    for name, (parameters, body) in SQL_FUNCTIONS.items():
        spark.sql(f"create or replace temporary function {name}({parameters}) returns double {body}")
