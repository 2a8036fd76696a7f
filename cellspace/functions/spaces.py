"""Feature spaces: a key and d double columns x0, x1, ... made from a table, in Spark and in plain SQL.

``frame`` leaves out rows with a null or NaN feature. Keys come from the table, or from a hash of its columns where it
has none, so that every tie can be broken.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cellspace.functions.loadings import LETTER_LOADINGS, LETTER_MEAN, LETTER_SPREAD, VECTOR_LOADINGS, VECTOR_MEAN

LINE_KEY = "concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, cast(round(l_extendedprice * 100) as bigint))"
LETTERS = "abcdefghijklmnopqrstuvwxyzàâçéèêîôùûäöü"


@dataclass(frozen=True)
class FeatureSpace:
    name: str
    table: str
    key: str  # Spark SQL
    features: tuple[str, ...]  # Spark SQL
    sql_key: str  # DuckDB
    sql_features: tuple[str, ...]
    extra: tuple[str, ...] = ()
    #: Steps before the features: (Spark SQL, DuckDB SQL) of named columns, each step over the one before.
    steps: tuple[tuple[tuple[str, str, str], ...], ...] = ()
    #: Spark SQL that is true of the rows whose features are all there; tested before they are made, so that long
    #: feature expressions aren't pushed down into a filter as well.
    valid: str = ""

    @property
    def dim(self) -> int:
        return len(self.features)

    @property
    def cols(self) -> list[str]:
        return [f"x{k}" for k in range(self.dim)]

    def frame(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        df = spark.read.parquet(f"{sf_dir}/{self.table}.parquet")
        if self.valid:
            df = df.where(self.valid)
        for step in self.steps:
            df = df.selectExpr(self.key, *self.extra, *[f"{e} AS {n}" for n, e, _ in step])
        df = df.selectExpr(f"{self.key} AS key", *[f"cast({e} AS double) AS x{k}" for k, e in enumerate(self.features)], *self.extra)
        return df if self.valid else clean(df, self.cols)

    def sql(self) -> str:
        cols = ", ".join(f"CAST({e} AS DOUBLE) AS x{k}" for k, e in enumerate(self.sql_features))
        some = " AND ".join(f"x{k} IS NOT NULL AND NOT isnan(x{k})" for k in range(self.dim))
        extra = "".join(f", {e}" for e in self.extra)
        source = self.table
        for step in self.steps:
            source = f"(SELECT {self.sql_key}{extra}, {', '.join(f'{e} AS {n}' for n, _, e in step)} FROM {source})"
        return f"SELECT * FROM (SELECT {self.sql_key} AS key, {cols}{extra} FROM {source}) WHERE {some}"


def clean(df: DataFrame, cols: list[str]) -> DataFrame:
    """Rows without null or NaN among ``cols``."""
    for c in cols:
        df = df.where(F.col(c).isNotNull() & ~F.isnan(c))
    return df


_SPARK_KEY = f"cast(conv(substring(md5({LINE_KEY}), 1, 15), 16, 10) as bigint)"
_DUCK_KEY = f"CAST('0x' || substr(md5({LINE_KEY}), 1, 15) AS BIGINT)"
_DAY = "datediff(cast(l_shipdate as date), date'1992-01-01')"
_DUCK_DAY = "date_diff('day', DATE '1992-01-01', CAST(l_shipdate AS DATE))"
_NET, _CHARGE = "l_extendedprice * (1 - l_discount)", "l_extendedprice * (1 - l_discount) * (1 + l_tax)"
_five = lambda day: ("l_quantity", "l_extendedprice / 1000", "l_discount * 100", "l_tax * 100", f"{day} / 100.0")
_charge = ("l_extendedprice * (1 - l_discount) / 1000", f"{_CHARGE} / 1000", "l_extendedprice / l_quantity / 100", f"ln({_CHARGE})", f"{_NET} * l_tax / 100")

LINE5 = FeatureSpace("line5", "lineitem", _SPARK_KEY, _five(_DAY), _DUCK_KEY, _five(_DUCK_DAY), ("l_returnflag",))
LINE3 = FeatureSpace("line3", "lineitem", _SPARK_KEY, tuple(_five(_DAY)[k] for k in (1, 2, 4)), _DUCK_KEY, tuple(_five(_DUCK_DAY)[k] for k in (1, 2, 4)))
LINE2 = FeatureSpace("line2", "lineitem", _SPARK_KEY, tuple(_five(_DAY)[k] for k in (1, 4)), _DUCK_KEY, tuple(_five(_DUCK_DAY)[k] for k in (1, 4)))
CHARGE5 = FeatureSpace("charge5", "lineitem", _SPARK_KEY, _charge, _DUCK_KEY, _charge)
EVENT3 = FeatureSpace("event3", "events", "event_id", ("(hour(ts) * 3600 + minute(ts) * 60 + second(ts)) / 3600.0", "value / 10", "get_json_object(props, '$.k')"), "event_id", ("(extract(hour FROM ts) * 3600 + extract(minute FROM ts) * 60 + floor(extract(second FROM ts))) / 3600.0", "value / 10", "json_extract_string(props, '$.k')"))


def _dot(terms: list[str], mean: tuple[float, ...], weights: tuple[float, ...]) -> str:
    return " + ".join(f"({t} - cast({m!r} as double)) * cast({w!r} as double)" for t, m, w in zip(terms, mean, weights, strict=True))


#: The text in lower case and its length, then the share of each letter in per cent.
_TEXT_STEP = (("folded", "lower(text)", "lower(text)"), ("n", "length(text)", "length(text)"))
_LETTER_STEP = tuple((f"c{k}", e, e) for k, c in enumerate(LETTERS) for e in [f"cast(length(folded) - length(replace(folded, '{c}', '')) as double) * cast(100 as double) / cast(greatest(n, 1) as double)"])
_C = [f"c{k}" for k in range(len(LETTERS))]
_PC = tuple(_dot(_C, LETTER_MEAN, w) for w in LETTER_LOADINGS)


def _doc_space(name: str, features: tuple[str, ...]) -> FeatureSpace:
    return FeatureSpace(name, "documents", "doc_id", features, "doc_id", features, ("lang",), (_TEXT_STEP, _LETTER_STEP), "text IS NOT NULL")


DOC39 = _doc_space("doc39", tuple(_C))
#: The first components of the letter shares, and the same with unit spread (whitened).
DOC5, DOC3, DOC2 = (_doc_space(f"doc{m}", _PC[:m]) for m in (5, 3, 2))
DOC5W, DOC3W = (_doc_space(f"doc{m}w", tuple(f"({e}) / cast({s!r} as double)" for e, s in zip(_PC[:m], LETTER_SPREAD[:m], strict=True))) for m in (5, 3))
_entry = lambda k, at: f"cast(embedding[{k + at}] as double)"
_vec = lambda at: tuple(_dot([_entry(k, at) for k in range(64)], VECTOR_MEAN, w) for w in VECTOR_LOADINGS)
_whole = "embedding IS NOT NULL AND size(embedding) >= 64 AND NOT exists(embedding, v -> v IS NULL OR isnan(v))"
EMB5 = FeatureSpace("emb5", "embeddings", "vec_id", _vec(0), "vec_id", _vec(1), ("label",), (), _whole)
EMB64 = FeatureSpace("emb64", "embeddings", "vec_id", tuple(_entry(k, 0) for k in range(64)), "vec_id", tuple(_entry(k, 1) for k in range(64)), ("label",), (), _whole)
SPACES = {s.name: s for s in (LINE5, LINE3, LINE2, CHARGE5, EVENT3, DOC5, DOC3, DOC2, DOC5W, DOC3W, DOC39, EMB5, EMB64)}


def letter_components(spark: SparkSession, sf_dir: str, m: int = 5) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(mean, loadings [39, m], spreads) fitted to the letter shares of a folder's documents."""
    mean, cov, _ = covariance(DOC39.frame(spark, sf_dir), DOC39.cols)
    w, v = eigen(cov)
    return mean, v[:, :m], np.sqrt(w[:m])


def standardise(df: DataFrame, cols: list[str]) -> tuple[DataFrame, dict[str, tuple[float, float]]]:
    """z columns of zero mean and unit spread (a column without spread becomes 0), and the (mean, spread) used."""
    row = df.agg(*[f(c).alias(f"{n}_{c}") for c in cols for n, f in (("m", F.avg), ("s", F.stddev_pop))]).first()
    stats = {c: (row[f"m_{c}"] or 0.0, row[f"s_{c}"] or 0.0) for c in cols}
    z = {f"z{k}": (F.col(c) - stats[c][0]) / stats[c][1] if stats[c][1] else F.lit(0.0) for k, c in enumerate(cols)}
    return df.withColumns(z), stats


def covariance(df: DataFrame, cols: list[str]) -> tuple[np.ndarray, np.ndarray, int]:
    """Mean, covariance and rows, from one aggregation over all pairs."""
    aggs = [F.avg(c).alias(f"m{i}") for i, c in enumerate(cols)] + [F.covar_pop(a, b).alias(f"c{i}_{j}") for i, a in enumerate(cols) for j, b in enumerate(cols) if i <= j]
    r = df.agg(F.count("*").alias("n"), *aggs).first()
    d = len(cols)
    cov = np.array([[r[f"c{min(i, j)}_{max(i, j)}"] or 0.0 for j in range(d)] for i in range(d)])
    return np.array([r[f"m{i}"] or 0.0 for i in range(d)]), cov, r["n"]


def fix_signs(loadings: np.ndarray) -> np.ndarray:
    """Columns whose entry of greatest size is positive."""
    top = np.abs(loadings).argmax(0)
    return loadings * np.where(loadings[top, np.arange(loadings.shape[1])] < 0, -1.0, 1.0)


def eigen(cov: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Eigenvalues (falling) and signed eigenvectors."""
    w, v = np.linalg.eigh(cov)
    order = np.argsort(-w)
    return np.maximum(w[order], 0), fix_signs(v[:, order])


def combine(cols: list[str], mean: np.ndarray, weights: np.ndarray) -> list[Column]:
    """Columns sum_j weights[j, k] * (cols[j] - mean[j])."""
    out = []
    for k in range(weights.shape[1]):
        e = F.lit(0.0)
        for c, m, w in zip(cols, mean, weights[:, k], strict=True):
            e = e + (F.col(c) - float(m)) * float(w)
        out.append(e)
    return out


def principal_components(df: DataFrame, cols: list[str], m: int = 3) -> tuple[DataFrame, np.ndarray, np.ndarray]:
    """pc1..pcm columns, the loadings [d, m] and the share of variance of each component."""
    mean, cov, _ = covariance(df, cols)
    w, v = eigen(cov)
    pcs = combine(cols, mean, v[:, :m])
    return df.withColumns({f"pc{k + 1}": c for k, c in enumerate(pcs)}), v[:, :m], w[:m] / max(w.sum(), 1e-300)


def whiten(df: DataFrame, cols: list[str]) -> tuple[DataFrame, np.ndarray]:
    """w columns with the unit matrix as covariance (directions without spread become 0), and the matrix used."""
    mean, cov, _ = covariance(df, cols)
    w, v = eigen(cov)
    scale = np.where(w > 1e-12 * max(w[0], 1e-300), 1 / np.sqrt(np.maximum(w, 1e-300)), 0.0)
    matrix = v * scale
    return df.withColumns({f"w{k}": c for k, c in enumerate(combine(cols, mean, matrix))}), matrix


def sphere_to_xyz(lon: Column, lat: Column, r: Column) -> list[Column]:
    """Cartesian columns of a position given by two angles in degrees and a radius."""
    a, b = F.radians(lon), F.radians(lat)
    return [F.cos(b) * F.cos(a) * r, F.cos(b) * F.sin(a) * r, F.sin(b) * r]


def linear_radius(z: Column, speed: float = 299_792.458, slope: float = 70.0) -> Column:
    """Distance proportional to redshift."""
    return z * (speed / slope)


def band_colours(vector: Column, curves: np.ndarray) -> list[Column]:
    """Differences of neighbouring bands; a band is ln of the vector weighted by its transmission curve."""
    bands = []
    for curve in curves:
        weighted = F.zip_with(vector, F.array(*[F.lit(float(c)) for c in curve]), lambda x, c: x * c)
        bands.append(F.ln(F.aggregate(weighted, F.lit(0.0), lambda s, x: s + x) + 1e-6))
    return [a - b for a, b in zip(bands, bands[1:], strict=False)]
