"""Temporary SQL functions, inlined by Catalyst, and the few Python functions that SQL has no words for."""

from __future__ import annotations

import unicodedata
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from blockflow.functions.taxonomy import class_sql
from blockflow.operators import statistics as S
from blockflow.operators.alias import ACCENTS, GENERIC

_DOT = "aggregate(zip_with({a}, {b}, (x, y) -> coalesce(x, 0d) * coalesce(y, 0d)), 0d, (s, v) -> s + v)"
_NORM = "sqrt(aggregate({a}, 0d, (s, v) -> s + v * v))"
_COSINE = f"case when {_NORM.format(a='a')} = 0 and {_NORM.format(a='b')} = 0 then 1d else least(1d, coalesce(try_divide({_DOT.format(a='a', b='b')}, {_NORM.format(a='a')} * {_NORM.format(a='b')}), 0d)) end"
_GAUSS = "exp(-gamma * aggregate(zip_with(p, q, (x, y) -> coalesce(x, 0d) - coalesce(y, 0d)), 0d, (s, v) -> s + v * v))"
_RATIO = "case when greatest(length(a), length(b)) = 0 then 100d else round(100 * (1 - levenshtein(a, b) / greatest(length(a), length(b))), 6) end"
_SORTED = "array_join(array_sort(split({a}, ' ')), ' ')"
_ENTROPY = "aggregate(transform(array_distinct(filter(split(t, ''), c -> c <> '')), c -> (length(t) - length(replace(t, c, ''))) / length(t)), 0d, (s, p) -> s - p * log2(p))"
_CLEAN = f"array_join(filter(split(trim(regexp_replace(translate(lower(t), '{ACCENTS[0]}', '{ACCENTS[1]}'), '[^a-z0-9]+', ' ')), ' '), w -> w not in ({', '.join(repr(x) for x in GENERIC)}, '')), ' ')"

#: name: (parameters, type, expression).
FUNCTIONS = {
    "bf_cosine": ("a array<double>, b array<double>", "double", _COSINE),
    "bf_gauss": ("p array<double>, q array<double>, gamma double", "double", _GAUSS),
    "bf_hybrid": ("a array<double>, b array<double>, p array<double>, q array<double>, gamma double", "double", f"({_COSINE}) * {_GAUSS}"),
    "bf_edit_ratio": ("a string, b string", "double", _RATIO),
    "bf_token_sort_ratio": ("a string, b string", "double", _RATIO.replace("levenshtein(a, b)", f"levenshtein({_SORTED.format(a='a')}, {_SORTED.format(a='b')})")),
    "bf_entropy": ("t string", "double", _ENTROPY),
    "bf_class_of": ("t string", "int", class_sql("t")),
    "bf_clean_alias": ("t string", "string", _CLEAN),
}


def register(spark: SparkSession) -> None:
    """Create the temporary functions of this session, and the table function blocks_of."""
    for name, (parameters, kind, body) in FUNCTIONS.items():
        spark.sql(f"create or replace temporary function {name}({parameters}) returns {kind} return {body}")
    spark.udtf.register("blocks_of", blocks_of)


@pandas_udf(T.StringType())
def normal_form(names: pd.Series) -> pd.Series:
    """Unicode compatibility form, which SQL has no function for; null stays null."""
    return names.map(lambda x: unicodedata.normalize("NFKC", x), na_action="ignore")


@pandas_udf(T.StructType().add("low", "double").add("high", "double"))
def _interval_of(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.DataFrame]:
    for k, n in batches:
        yield pd.DataFrame([S.exact_interval(int(a), int(b)) if b else (0.0, 1.0) for a, b in zip(k, n, strict=True)], columns=["low", "high"])


def exact_intervals(df, grp: str, right: str):
    """grp, n, k, low, high: the exact interval of the share of rows where `right` holds, for each stratum; sums first, so only counts meet Python."""
    sums = df.groupBy(grp).agg(F.count(F.lit(1)).alias("n"), F.sum(F.expr(right).cast("int")).cast("long").alias("k"))
    return sums.withColumn("i", _interval_of("k", "n")).select(grp, "n", "k", F.round("i.low", 6).alias("low"), F.round("i.high", 6).alias("high"))


@udtf(returnType=T.StructType().add("func_id", "integer").add("block_id", "integer").add("n", "integer").add("body", "string"))
class blocks_of:
    """Blocks of a text: a line is a function, a clause a block, a word an instruction. The carriers do the same in SQL."""

    def eval(self, text: str):
        import re

        lines = [x.strip(" ") for x in (text or "").split("\n")]
        for k, line in enumerate(x for x in lines if x):
            for i, part in enumerate(p for p in (x.strip(" ") for x in re.split("[.!?,;]+", line)) if p):
                yield k, i, len([w for w in re.split("[ \\t\\n\\x0b\\f\\r]+", part) if w]), part
