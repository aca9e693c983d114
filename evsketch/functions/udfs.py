"""SQL functions, a grouped Arrow aggregate, a table function and a small fluent class."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evsketch.functions.gumbel import EULER_GAMMA
from evsketch.operators import estimate as est
from evsketch.operators import registers as rg
from evsketch.spec import SketchSpec

#: name -> (arguments, returns, body); Spark inlines the bodies into the plan.
SQL_FUNCTIONS = {
    "gumbel_cdf": ("x double, mu double", "double", "exp(-exp(-(x - mu)))"),
    "gumbel_pdf": ("x double, mu double", "double", "exp(-exp(-(x - mu)) - (x - mu))"),
    "gumbel_quantile": ("t double, mu double", "double", "mu - ln(-ln(t))"),
    "shift_round": ("x double, c double", "double", "floor(x + c) - c"),
    "estimate_from_mean": ("k int, mean double", "double", f"k * exp(mean - {EULER_GAMMA}D)"),
}


def register_sql(spark: SparkSession) -> None:
    """Makes the scalar functions and the table function sketch_spine(k) known to SQL."""
    for name, (args, returns, body) in SQL_FUNCTIONS.items():
        spark.sql(f"create or replace temporary function {name}({args}) returns {returns} return {body}")
    spark.sql("create or replace temporary function sketch_spine(k int) returns table(reg int) return select explode(sequence(0, k - 1)) as reg")


def grouped_gumbel_distinct(df: DataFrame, by: str, col: str, k: int = 64) -> DataFrame:
    """Distinct count per group by one Arrow call a group: for ad-hoc use on small groups; the
    two-phase registers are the default. Equals the unseeded averaged geometric estimate."""
    import hashlib

    kind = df.schema[by].dataType.simpleString()

    def one(table: pa.Table) -> pa.Table:
        low: dict[int, int] = {}
        for v in set(table.column("item").to_pylist()):
            h = hashlib.md5(f"s1:{v}".encode()).hexdigest()
            reg, w = int(h[16:24], 16) % k, int(h[:13], 16)
            low[reg] = min(w, low.get(reg, w))
        u = (np.fromiter(low.values(), float) + 0.5) / 2.0**52
        z = k * np.exp(np.mean(-np.log(-np.log1p(-u))) - EULER_GAMMA) if low else 0.0
        return pa.table({by: table.column(by).slice(0, 1), "z": pa.array([float(z)])})

    return rg.items(df, col, [by]).groupBy(by).applyInArrow(one, f"`{by}` {kind}, z double")


def explode_registers_udtf():
    """A table function (qs binary) -> (reg, q): a byte a register, 128 more than q; 0 for none."""

    @F.udtf(returnType="reg: int, q: int")
    class ExplodeRegisters:
        def eval(self, qs: bytes):
            for i, b in enumerate(qs or b""):
                if b:
                    yield i, b - 128

    return ExplodeRegisters


def binary_registers(packed: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """qs array<tinyint> as binary for the table function."""
    text = F.array_join(F.transform("qs", lambda q: F.lpad(F.hex(q.cast("int") + 128), 2, "0")), "")
    return packed.select(*by, F.unhex(text).alias("qs"))


class Sketch:
    """``Sketch(df).of("user_id").by("day").with_k(256).estimate("harmonic")``."""

    def __init__(self, df: DataFrame, cols=None, by: Sequence[str] = (), spec: SketchSpec = SketchSpec()):
        self._df, self._cols, self._by, self.spec = df, cols, list(by), spec

    def of(self, *cols: str) -> Sketch:
        return Sketch(self._df, list(cols), self._by, self.spec)

    def by(self, *by: str) -> Sketch:
        return Sketch(self._df, self._cols, by, self.spec)

    def with_k(self, k: int) -> Sketch:
        return Sketch(self._df, self._cols, self._by, self.spec.with_(k=k))

    def registers(self) -> DataFrame:
        regs = rg.registers(self._df, self._cols, self._by, self.spec)
        return rg.with_seed_draws(regs, self.spec, self._by) if self.spec.init == "seeded" else regs

    def estimate(self, kind: str = "geometric") -> DataFrame:
        answers = {"geometric": est.estimate_geometric, "harmonic": est.estimate_harmonic, "inverted": est.estimate_harmonic_inverted}
        return answers[kind](self.registers(), self.spec, self._by)
