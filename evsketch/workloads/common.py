"""Registry of queries, and the DuckDB expressions of the portable family."""

from __future__ import annotations

import os
import zlib
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from evsketch.functions.gumbel import EULER_GAMMA
from evsketch.spec import SketchSpec

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

#: Registers at every size, those of the oracles; and exceptions by the input's name (none).
K = 256
K_BY_SIZE: dict[str, int] = {}
#: Registers where every register sees every item, and in many-seed runs.
K_FULL = 64
SEEDS = 60


def query(sql: str | None = None):
    """Registers a function under its name, with the DuckDB text that gives the same rows."""

    def add(fn: Query) -> Query:
        QUERIES[fn.__name__] = fn
        if sql is not None:
            ORACLES[fn.__name__] = sql
        return fn

    return add


def registers_at(sf_dir: str) -> int:
    return K_BY_SIZE.get(os.path.basename(sf_dir.rstrip("/")), K)


def spec_at(sf_dir: str, **more) -> SketchSpec:
    return SketchSpec(k=registers_at(sf_dir), **more)


# -- DuckDB text -----------------------------------------------------------------------------

TOP = "0.99999999999999988897769753748::double"
WORD = "4503599627370496::double"


def md(item: str, seed: str = "'s1'", tag: str = "") -> str:
    return f"md5({seed} || '{tag}:' || cast({item} as varchar))"


def w(item: str, seed: str = "'s1'", tag: str = "") -> str:
    return f"cast('0x' || substr({md(item, seed, tag)}, 1, 13) as bigint)"


def r(item: str, k: int | str = K, seed: str = "'s1'") -> str:
    return f"(cast('0x' || substr({md(item, seed)}, 17, 8) as bigint) % {k})"


def wf(item: str, i: str = "i", seed: str = "'s1'") -> str:
    return f"cast('0x' || substr(md5({seed} || '/' || cast({i} as varchar) || ':' || cast({item} as varchar)), 1, 13) as bigint)"


def c(reg: str, seed: str = "'s1'") -> str:
    return f"({w(reg, seed, '#off')} / {WORD})"


def u(col: str) -> str:
    return f"least((cast({col} as double) + 0.5::double) / {WORD}, {TOP})"


def e(col: str) -> str:
    """-ln(1-u), exact for small u."""
    return f"(2 * atanh({u(col)} / (2 - {u(col)})))"


def x(col: str) -> str:
    return f"(-ln({e(col)}))"


def regs(table: str, item: str, by: str = "", k: int = K, seed: str = "'s1'") -> str:
    lead = f"{by}, " if by else ""
    return f"(select {lead}{r(item, k, seed)} as reg, min({w(item, seed)}) as w from {table} where ({item}) is not null group by all)"


def seeded(regs_: str, by: str = "", k: int = K, seed: str = "'s1'") -> str:
    spine = f"(select i as reg, {w('i', seed, '#reg')} as w from range({k}) t(i))"
    if by:
        return f"(select {by}, reg, min(w) as w from (select {by}, reg, w from {regs_} union all select {by}, s.reg, s.w from (select distinct {by} from {regs_}) g cross join {spine} s) group by all)"
    return f"(select reg, min(w) as w from (select reg, w from {regs_} union all select reg, w from {spine}) group by all)"


def full(table: str, item: str, by: str = "", k: int = K_FULL) -> str:
    lead = f"{by}, " if by else ""
    return f"(select {lead}i as reg, min({wf(item)}) as w from (select distinct {lead}{item} as {item} from {table}) cross join range({k}) t(i) group by all)"


def geo(source: str, factor: float, by: str = "", out: str = "z") -> str:
    lead = f"{by}, " if by else ""
    tail = f" group by {by}" if by else ""
    return f"select {lead}round({factor} * exp(avg({x('w')}) - {EULER_GAMMA}), 6) as {out} from {source}{tail}"


def harm(source: str, scale: float, by: str = "", out: str = "z") -> str:
    lead = f"{by}, " if by else ""
    tail = f" group by {by}" if by else ""
    return f"select {lead}round({scale} / sum({e('w')}), 6) as {out} from {source}{tail}"


# -- DuckDB text of the fast family ------------------------------------------------------------

#: The five primes of the public 64-bit xxHash (fixed values).
XX_PRIMES = (11400714785074694791, 14029467366897019727, 1609587929392839161, 9650029242287828579, 2870177450012600261)


def _fit(value: str) -> str:
    return f"(({value}) % '18446744073709551616'::uhugeint)"


def _times(value: str, prime: int) -> str:
    return _fit(f"{value} * '{XX_PRIMES[prime - 1]}'::uhugeint")


def _plus(value: str, prime: int) -> str:
    return _fit(f"{value} + '{XX_PRIMES[prime - 1]}'::uhugeint")


def _turned(value: str, bits: int) -> str:
    return f"({_fit(f'{value} << {bits}')} | ({value} >> {64 - bits}))"


def _little(first: str, size: int) -> str:
    """``size`` bytes of the list b after the first ``first`` ones, as a number."""
    return "(" + " + ".join(f"(b[{first} + {i + 1}]::uhugeint << {8 * i})" for i in range(size)) + ")"


def xx(source: str, name: str) -> str:
    """CTEs that end in ``name``: rows of ``source`` with h, a seed, replaced by the hash of the bytes
    b (a list of at most 31) under it."""
    length, steps = "len(b)", []
    for i in range(3):
        mixed = f"xor(h, {_times(_turned(_times('g', 2), 31), 1)})"
        steps.append((f"{length} >= {8 * i + 8}", _little(str(8 * i), 8), mixed, 27, 1, 4))
    steps.append((f"{length} % 8 >= 4", _little(f"({length} - {length} % 8)", 4), f"xor(h, {_times('g', 1)})", 23, 2, 3))
    for i in range(3):
        steps.append((f"{length} % 4 > {i}", _little(f"({length} - {length} % 4 + {i})", 1), f"xor(h, {_times('g', 5)})", 11, 1, 0))
    out, at = [f"{name}_0 as (select * replace ({_plus(f'h + {length}::uhugeint', 5)} as h) from {source})"], 0
    for holds, group, mixed, bits, times, plus in steps:
        out.append(f"{name}_{at + 1} as (select *, case when {holds} then {group} end as g from {name}_{at})")
        out.append(f"{name}_{at + 2} as (select * exclude (g) replace (case when g is null then h else {mixed} end as h), g is not null as hit from {name}_{at + 1})")
        new = _times(_turned("h", bits), times)
        out.append(f"{name}_{at + 3} as (select * exclude (hit) replace (case when hit then {_plus(new, plus) if plus else new} else h end as h) from {name}_{at + 2})")
        at += 3
    for shift, prime in ((33, 2), (29, 3), (32, 0)):
        mixed = f"xor(h, h >> {shift})"
        out.append(f"{name}_{at + 1} as (select * replace ({_times(mixed, prime) if prime else mixed} as h) from {name}_{at})")
        at += 1
    return ", ".join([*out, f"{name} as (select * from {name}_{at})"])


def fast_dense(table: str, item: str, k: int = K, seed: str = "s1") -> str:
    """CTEs that end in ``dense`` (reg, w): seeded averaged registers of an integer column by the fast family; k
    is a power of two (signed and unsigned remainders agree)."""
    marks = [(what, zlib.crc32(f"{seed}{what}".encode())) for what in ("#reg", "#draw", "#start")]
    rows = ", ".join(f"('{what}', [{', '.join(str(n >> 8 * i & 255) for i in range(4 if n < 1 << 31 else 8))}])" for what, n in marks)
    text = "list_transform(string_split(cast(v as varchar), ''), lambda y: ascii(y))"
    return f"""
marks as (select what, b, 42::uhugeint as h from (values {rows}) t(what, b)), {xx("marks", "seeds")},
inputs as (
  select what, v, {text} as b, h from (select distinct {item} as v from {table} where {item} is not null) cross join (select what, h from seeds where what <> '#start')
  union all select what, i, [i % 256, i // 256, 0, 0], h from range({k}) t(i) cross join (select what, h from seeds where what = '#start')
), {xx("inputs", "hashed")},
draws as (
  select cast(a.h % {k} as bigint) as reg, b.h >> 1 as w from hashed a join hashed b on a.v = b.v and a.what = '#reg' and b.what = '#draw'
  union all select v, h >> 1 from hashed where what = '#start'
),
dense as (select reg, min(w) as w from draws group by reg)"""
