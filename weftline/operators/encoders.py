"""Encoders: statistics that merge into one aggregate, driver-sized states, native applies.

An encoder is a plain dict (so that it is a parameter of a plan): ``kind``, ``cols`` and
options.  Fitting asks every encoder for its aggregate columns, runs them as one job, and
lets those that need groups run their own; applying yields one projection, with joins only
for categories beyond a checked number.
"""

from __future__ import annotations

import json
import math
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from .merge import summed
from .order import exact_quantiles

#: Categories up to which a state becomes an expression; beyond it, a joined table.
INLINE_CATEGORIES = 256
#: Metadata of columns that hold zeros and ones alone.
FLAG = "weftline_flag"
NULL_TOKENS = ("", "n/a", "na", "null", "none", "nan", "-")


def key_of(encoder: dict) -> str:
    return json.dumps(encoder, sort_keys=True)


def cleaned(column: Column, tokens: tuple[str, ...] = NULL_TOKENS) -> Column:
    """Trimmed; null-like tokens become null."""
    text = F.trim(column)
    return F.when(F.lower(text).isin(list(tokens)), F.lit(None)).otherwise(text)


def impute_value(column: str, how: str, constant: object = 0) -> Column:
    c = F.col(column)
    return {
        "mean": lambda: F.avg(c), "median": lambda: F.percentile(c, 0.5), "approx_median": lambda: F.percentile_approx(c, 0.5, 10_000),
        "const": lambda: F.first(F.lit(constant)),
        "mode": lambda: F.mode(c, True),
    }[how]()


def char_ngrams(text: Column, n: int) -> Column:
    """Character n-grams of a text, none of shorter texts; linear in its length."""
    chars = F.split(text, "")
    grams = chars
    for k in range(1, n):
        grams = F.zip_with(grams, F.slice(chars, k + 1, 2_000_000_000), lambda a, b: F.concat(a, b))
    return F.when(F.length(text) >= n, F.slice(grams, F.lit(1), F.length(text) - (n - 1))).otherwise(F.array().cast("array<string>"))


def padded(text: Column) -> Column:
    return F.concat(F.lit(" "), F.lower(F.trim(F.regexp_replace(text, r"\s+", " "))), F.lit(" "))


def statistics(encoder: dict) -> dict[str, Column]:
    """Aggregates that fitting needs of the training rows."""
    kind, out = encoder["kind"], {}
    if kind == "numeric":
        for c in encoder["cols"]:
            out[f"n {c}"] = F.count(c)
            if encoder.get("impute") != "median":  # those come from ``exact_quantiles``
                out[f"v {c}"] = impute_value(c, encoder.get("impute", "mean"), encoder.get("constant", 0))
            out[f"m {c}"], out[f"d {c}"] = F.avg(F.col(c).cast("double")), F.var_pop(F.col(c).cast("double"))
        out["rows"] = F.count(F.lit(1))
    return out


def fit_all(df: DataFrame, encoders: list[dict], train: str, target: str) -> dict[str, dict]:
    """States by encoder: one merged aggregate, and a grouped job for each encoder of categories."""
    rows = df.filter(train)
    merged = {f"{k}|{name}": col for k, e in enumerate(encoders) for name, col in statistics(e).items()}
    found = rows.agg(*[col.alias(name) for name, col in merged.items()]).first().asDict() if merged else {}
    middle = sorted({c for e in encoders if e["kind"] == "numeric" and e.get("impute") == "median" for c in e["cols"]})
    medians = exact_quantiles(rows, middle) if middle else {}
    out: dict[str, dict] = {}
    grams: dict[str, tuple] = {}  # those of a text column, for all encoders that differ in their components alone
    for k, e in enumerate(encoders):
        mine = {name.partition("|")[2]: v for name, v in found.items() if name.startswith(f"{k}|")}
        if e.get("impute") == "median":
            mine |= {f"v {c}": medians[c] for c in e["cols"]}
        if e["kind"] == "text":
            mine["grams"] = grams
        try:
            out[key_of(e)] = FITS[e["kind"]](rows, e, mine, target)
        except MemoryError as error:  # told to those that apply it; other users of a merged fit go on
            out[key_of(e)] = {"error": error}
    return out


def fit_numeric(rows: DataFrame, e: dict, found: dict, target: str) -> dict:
    state = {}
    for c in e["cols"]:
        n, have = found["rows"], found[f"n {c}"]
        value = float(found[f"v {c}"]) if found[f"v {c}"] is not None else 0.0
        own, spread = found[f"m {c}"] or 0.0, found[f"d {c}"] or 0.0
        mean = (have * own + (n - have) * value) / n if n else 0.0
        std = math.sqrt(max(0.0, (have * (spread + (own - mean) ** 2) + (n - have) * (value - mean) ** 2) / n)) if n else 0.0
        state[c] = (value, mean if e.get("scale", True) else 0.0, (std if std > 1e-12 * (abs(mean) + 1) else 1.0) if e.get("scale", True) else 1.0)
    return state


def fit_onehot(rows: DataFrame, e: dict, found: dict, target: str) -> dict:
    """Categories in order; rare ones share one column, unseen ones have zeros."""
    cols, most = e["cols"], e.get("max_categories", INLINE_CATEGORIES)
    values = F.array(*[F.struct(F.lit(k).alias("k"), cleaned(F.col(c).cast("string")).alias("v")) for k, c in enumerate(cols)])
    counts = rows.select(F.explode(values).alias("r")).select("r.*").filter("v is not null").groupBy("k", "v").count()
    got = counts.orderBy("k", "v").limit((most + 1) * len(cols)).collect()
    state = {}
    for k, c in enumerate(cols):
        mine = [r for r in got if r["k"] == k]
        if len(mine) > most or len(got) > most * len(cols):
            raise MemoryError(f"{c if len(mine) > most else cols} has more than {most} categories: one-hot columns would pass the memory bound")
        least = e.get("min_count", 1)
        state[c] = ([r["v"] for r in mine if r["count"] >= least], [r["v"] for r in mine if r["count"] < least])
    return state


#: Rows of a state's table, and bytes of a text in it, up to which it is brought to the driver and broadcast.
LOCAL_ROWS, LOCAL_BYTES = 20_000, 1_000


def local_sums(sums: DataFrame) -> tuple[DataFrame, bool]:
    """The sums as a local table if they are few, so that applying them neither computes them again nor shuffles rows by a skewed key."""
    long = F.octet_length("v") > LOCAL_BYTES
    found = sums.select(*[F.when(long, F.lit(None)).otherwise(F.col("v")).alias("v") if c == "v" else F.col(c) for c in sums.columns], F.coalesce(long, F.lit(False)).alias("_long"))
    rows = found.limit(LOCAL_ROWS + 1).collect()
    if len(rows) > LOCAL_ROWS or any(r["_long"] for r in rows):
        return sums, False
    return sums.sparkSession.createDataFrame([tuple(r)[:-1] for r in rows], sums.schema), True


def target_sums(rows: DataFrame, column: str, target: str, fold: str | None = None) -> DataFrame:
    by = [F.col(column).cast("string").alias("v"), *([F.col(fold).alias("fold")] if fold else [])]
    return rows.groupBy(*by).agg(F.sum(F.col(target).cast("double")).alias("s"), F.count(target).alias("n"))


def fit_target(rows: DataFrame, e: dict, found: dict, target: str) -> dict:
    """Per column and category sums of the target by fold; the table stays distributed when large."""
    state = {}
    for c in e["cols"]:
        sums, local = local_sums(target_sums(rows, c, target, e.get("fold")))
        parts = sums.groupBy(*(["fold"] if e.get("fold") else [])).agg(F.sum("s").alias("s"), F.sum("n").alias("n")).collect()
        total = (sum(r["s"] or 0.0 for r in parts), sum(r["n"] or 0 for r in parts))
        state[c] = {"sums": sums, "local": local, "total": total, "folds": {r["fold"]: (r["s"], r["n"]) for r in parts} if e.get("fold") else {}}
    return state


def sizes_of(e: dict) -> list[int]:
    n = e.get("ngram", 3)
    return [n] if isinstance(n, int) else list(range(n[0], n[1] + 1))


def terms(text: Column, e: dict) -> Column:
    """The n-grams of a text, of all sizes asked for: characters (padded, ``char_wb``, or not, ``char``) or words."""
    analyzer = e.get("analyzer", "char_wb")
    if analyzer == "word":
        words = F.filter(F.split(F.lower(text), r"\s+"), lambda w: w != "")
        grams = [word_ngrams(words, n) for n in sizes_of(e)]
    else:
        plain = padded(text) if analyzer == "char_wb" else F.lower(text)
        grams = [char_ngrams(plain, n) for n in sizes_of(e)]
    out = grams[0] if len(grams) == 1 else F.concat(*grams)
    if e.get("vectorizer") == "hash":
        buckets = e.get("vocabulary", 1000)
        out = F.transform(out, lambda g: (F.crc32(g.cast("binary")) % buckets).cast("string"))
    return out


def word_ngrams(words: Column, n: int) -> Column:
    starts = F.sequence(F.lit(1), F.greatest(F.size(words) - (n - 1), F.lit(1)))
    joined = F.transform(starts, lambda i: F.array_join(F.slice(words, i, n), " "))
    return F.when(F.size(words) >= n, joined).otherwise(F.array().cast("array<string>"))


def row_terms(text: str, e: dict) -> list[str]:
    """The same in Python, for one text."""
    analyzer, grams = e.get("analyzer", "char_wb"), []
    if analyzer == "word":
        words = text.lower().split()
        for n in sizes_of(e):
            grams += [" ".join(words[k : k + n]) for k in range(len(words) - n + 1)]
    else:
        plain = f" {' '.join(text.lower().split())} " if analyzer == "char_wb" else text.lower()
        for n in sizes_of(e):
            grams += [plain[k : k + n] for k in range(len(plain) - n + 1)]
    if e.get("vectorizer") == "hash":
        grams = [str(zlib.crc32(g.encode()) % e.get("vocabulary", 1000)) for g in grams]
    return grams


def text_counts(strings: DataFrame, e: dict | int) -> DataFrame:
    """(v, w, gram, tf) for distinct strings v of weight w."""
    e = {"ngram": e} if isinstance(e, int) else e
    return strings.select("v", "w", F.explode(terms(F.col("v"), e)).alias("gram")).groupBy("v", "w", "gram").agg(F.count("*").alias("tf"))


def fit_text(rows: DataFrame, e: dict, found: dict, target: str) -> dict:
    """Latent components of n-gram tf-idf: distinct strings only, weighted by their frequency.

    The vocabulary holds the ``vocabulary`` terms of most documents, as its Gram
    matrix must fit the driver; with ``vectorizer`` hash every term counts, in that many buckets.
    """
    state = {}
    grams = found.get("grams", {})
    for c in e["cols"]:
        key = json.dumps([c, {k: v for k, v in e.items() if k not in ("cols", "n_components")}], sort_keys=True)
        if key not in grams:
            grams[key] = term_gram(rows, c, e)
        idf, gram = grams[key]
        values, vectors = np.linalg.eigh(gram) if len(gram) else (np.empty(0), np.empty((0, 0)))
        order = np.argsort(-values, kind="stable")[: e["n_components"]]
        v = vectors[:, order]
        if v.size:
            v = v * np.where(v[np.abs(v).argmax(0), np.arange(v.shape[1])] < 0, -1, 1)
        state[c] = {"idf": idf, "v": v}
    return state


def term_gram(rows: DataFrame, c: str, e: dict) -> tuple[dict[str, float], np.ndarray]:
    """Inverse document frequencies of the vocabulary of a column, and its Gram matrix."""
    strings = rows.select(F.col(c).alias("v")).filter("v is not null").groupBy("v").agg(F.count("*").alias("w")).persist()
    try:
        total, distinct = strings.agg(F.sum("w"), F.count(F.lit(1))).first()
        total = total or 0
        counts = text_counts(strings, e)
        vocabulary = counts.groupBy("gram").agg(F.sum("w").alias("df")).orderBy(F.desc("df"), "gram").limit(e.get("vocabulary", 1000)).collect()
        idf = {r["gram"]: math.log((1 + total) / (1 + r["df"])) + 1 for r in vocabulary}
        return idf, weighted_gram(strings, idf, e, max(1, distinct // GRAM_STRINGS))
    finally:
        strings.unpersist()


def tfidf(texts: list[str | None], idf: dict[str, float], e: dict) -> np.ndarray:
    at = {g: k for k, g in enumerate(idf)}
    weight = np.array(list(idf.values()))
    out = np.zeros((len(texts), len(idf)))
    for i, t in enumerate(texts):
        if t is not None:
            for g in row_terms(t, e):
                j = at.get(g)
                if j is not None:
                    out[i, j] += weight[j]
    norm = np.linalg.norm(out, axis=1, keepdims=True)
    return out / np.where(norm > 0, norm, 1)


#: Distinct strings that a task has at least: its part is a whole matrix however few they are.
GRAM_STRINGS = 2048


def weighted_gram(strings: DataFrame, idf: dict[str, float], e: dict, tasks: int | None = None) -> np.ndarray:
    """Sum of w xᵀx over distinct strings by partial sums, merged in parallel; ``tasks`` at most, where given."""
    p = len(idf)

    def run(batches):
        total, seen = np.zeros((p, p)), False
        for pdf in batches:
            for begin in range(0, len(pdf), 2048):
                part = pdf.iloc[begin : begin + 2048]
                x = tfidf(part["v"].tolist(), idf, e)
                total += (x * part["w"].to_numpy()[:, None]).T @ x
                seen = True
        if seen:  # most tasks have no string where there are few
            yield pd.DataFrame({"b": [0], "m": [total.tobytes()]})

    few = strings.coalesce(tasks) if tasks else strings
    return summed(few.mapInPandas(run, "b int, m binary"), tasks, 8.0 * p * p).get(0, np.zeros(p * p)).reshape(p, p)


def fit_none(rows: DataFrame, e: dict, found: dict, target: str) -> dict:
    return {}


FITS = {"numeric": fit_numeric, "onehot": fit_onehot, "target": fit_target, "text": fit_text, "dates": fit_none}


def date_parts(column: str) -> dict[str, Column]:
    c = F.col(column)
    return {"year": F.year(c), "month": F.month(c), "day": F.dayofmonth(c), "dow": F.dayofweek(c), "epoch": F.unix_date(c.cast("date"))}


def apply_all(df: DataFrame, encoders: list[dict], states: dict[str, dict], carry: list[str], train: str) -> tuple[DataFrame, list[str]]:
    """``carry`` and the features, named f_<column>…; row-preserving."""
    out: dict[str, Column] = {}
    flags: set[str] = set()
    for e in encoders:
        state = states[key_of(e)]
        if "error" in state:
            raise state["error"]
        for c in e["cols"]:
            if e["kind"] == "numeric":
                value, mean, std = state[c]
                out[f"f_{c}"] = (F.coalesce(F.col(c).cast("double"), F.lit(value)) - F.lit(mean)) / F.lit(std)
                if e.get("indicator"):
                    out[f"f_{c}_missing"] = F.col(c).isNull().cast("double")
            elif e["kind"] == "onehot":
                kept, rare = state[c]
                text = cleaned(F.col(c).cast("string"))
                at = f"_at_{c}_{len(out)}"  # cleaned and looked up once a row, not once a category
                df = df.withColumn(at, F.coalesce(F.array_position(F.array(*map(F.lit, [*kept, *rare])).cast("array<string>"), text), F.lit(0)))
                first = 1 if e.get("drop_first", True) else 0
                own = {f"f_{c}_{k}": (F.col(f"`{at}`") == k + first + 1).cast("double") for k in range(len(kept[first:]))}
                if rare:
                    own[f"f_{c}_rare"] = (F.col(f"`{at}`") > len(kept)).cast("double")
                out |= own
                flags |= set(own)
            elif e["kind"] == "dates":
                out |= {f"f_{c}_{k}": v.cast("double") for k, v in date_parts(c).items()}
            elif e["kind"] == "target":
                df, out[f"f_{c}_mean"] = with_target(df, c, e, state[c], train)
            elif e["kind"] == "text":
                df, vector = with_components(df, c, e, state[c])
                out |= {f"f_{c}_part{k}": F.coalesce(F.get(vector, F.lit(k)), F.lit(0.0)) for k in range(state[c]["v"].shape[1])}
    return df.select(*carry, *[v.alias(k, metadata={FLAG: True}) if k in flags else v.alias(k) for k, v in out.items()]), list(out)


#: Columns of zeros and ones up to which each is kept as bytes; more of them are bits of one number.
FLAGS_APART, FLAG_BITS = 8, 62


def narrowed(df: DataFrame) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """A frame to keep, its columns of zeros and ones as bytes or, many of them, as bits, and what gives them back as they were."""
    flags = [f.name for f in df.schema if f.metadata.get(FLAG)]
    if len(flags) > FLAGS_APART:
        return packed(df, flags)

    def typed(frame: DataFrame, kind: str) -> DataFrame:
        return frame.select(*[F.col(f"`{c}`").cast(kind).alias(c, metadata={FLAG: True}) if c in flags else F.col(f"`{c}`") for c in frame.columns])

    return typed(df, "tinyint"), lambda kept: typed(kept, "double")


def packed(df: DataFrame, flags: list[str]) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """The same with the flags as bits of as few numbers as hold them: keeping a frame takes time by column."""
    name = "_bits"
    while any(c.startswith(name) for c in df.columns):
        name = f"_{name}"
    place = {c: (f"{name}{k // FLAG_BITS}", k % FLAG_BITS) for k, c in enumerate(flags)}
    bits: dict[str, Column] = {}
    for begin in range(0, len(flags), FLAG_BITS):  # folded: a sum written out makes code that the JVM doesn't compile
        own = F.array(*[F.coalesce(F.col(f"`{c}`") != 0, F.lit(False)) for c in reversed(flags[begin : begin + FLAG_BITS])])
        bits[place[flags[begin]][0]] = F.aggregate(own, F.lit(0).cast("bigint"), lambda sums, flag: F.shiftleft(sums, 1) + flag.cast("bigint"))

    def one(c: str) -> Column:
        if c not in place:
            return F.col(f"`{c}`")
        to, k = place[c]
        return F.shiftright(F.col(to), k).bitwiseAND(F.lit(1).cast("bigint")).cast("double").alias(c, metadata={FLAG: True})

    kept = df.select(*[F.col(f"`{c}`") for c in df.columns if c not in place], *[v.alias(k) for k, v in bits.items()])

    def widened(frame: DataFrame) -> DataFrame:
        out = frame.select(*map(one, df.columns))
        out._weftline_packed = (frame, place)
        return out

    return kept, widened


def packed_form(df: DataFrame) -> tuple[DataFrame, dict[str, tuple[str, int]]] | None:
    """The same rows with flags as bits, (number's column, bit) by flag, where the frame comes from such."""
    return getattr(df, "_weftline_packed", None)


def filtered(df: DataFrame, condition: str) -> DataFrame:
    """The rows of a condition, their packed form kept where the condition needs no flag."""
    out, told = df.filter(condition), packed_form(df)
    if told is not None and not any(c in condition for c in told[1]):
        out._weftline_packed = (told[0].filter(condition), told[1])
    return out


def with_target(df: DataFrame, c: str, e: dict, state: dict, train: str) -> tuple[DataFrame, Column]:
    """Smoothed means; training rows get those of the other folds, unseen categories the mean."""
    m, (total, n) = float(e.get("smoothing", 10.0)), state["total"]
    mean = total / n if n else 0.0
    sent = F.broadcast if state.get("local") else lambda table: table
    whole = state["sums"].groupBy("v").agg(F.sum("s").alias("_s"), F.sum("n").alias("_n"))
    joined = df.join(sent(whole.withColumnsRenamed({"v": f"_v_{c}", "_s": f"_s_{c}", "_n": f"_n_{c}"})), df[c].cast("string") == F.col(f"_v_{c}"), "left")
    s, k = F.coalesce(F.col(f"_s_{c}"), F.lit(0.0)), F.coalesce(F.col(f"_n_{c}"), F.lit(0))
    full = (s + m * mean) / (k + m) if m else F.when(k > 0, s / k).otherwise(F.lit(mean))
    if not e.get("fold"):
        return joined, full
    per_fold = state["sums"].select(F.col("v").alias(f"_w_{c}"), F.col("fold").alias(f"_f_{c}"), F.col("s").alias(f"_t_{c}"), F.col("n").alias(f"_k_{c}"))
    joined = joined.join(sent(per_fold), (F.col(f"_v_{c}") == F.col(f"_w_{c}")) & (F.col(e["fold"]) == F.col(f"_f_{c}")), "left")
    s, k = s - F.coalesce(F.col(f"_t_{c}"), F.lit(0.0)), k - F.coalesce(F.col(f"_k_{c}"), F.lit(0))
    rest = F.lit(mean)
    for fold, (fs, fn) in state["folds"].items():
        rest = F.when(F.col(e["fold"]) == fold, F.lit((total - fs) / (n - fn) if n > fn else mean)).otherwise(rest)
    out_of_fold = (s + m * rest) / (k + m) if m else F.when(k > 0, s / k).otherwise(rest)
    return joined, F.when(F.expr(train), out_of_fold).otherwise(full)


def with_components(df: DataFrame, c: str, e: dict, state: dict) -> tuple[DataFrame, Column]:
    """Distinct strings are projected once and joined back; few short ones on the driver, as a table that is broadcast."""
    idf, v = state["idf"], state["v"]
    long = F.octet_length(c) > LOCAL_BYTES
    texts = df.filter(F.col(c).isNotNull()).select(F.when(~long, F.col(c)).alias("v")).distinct().limit(LOCAL_ROWS + 1).collect()
    if len(texts) <= LOCAL_ROWS and all(r["v"] is not None for r in texts):
        told = []
        for k in range(0, len(texts), 2048):
            own = [r["v"] for r in texts[k : k + 2048]]
            told += zip(own, (tfidf(own, idf, e) @ v).tolist())
        few = df.sparkSession.createDataFrame(told, f"`_text_{c}` string, `_parts_{c}` array<double>")
        return df.join(F.broadcast(few), df[c] == few[f"_text_{c}"], "left"), F.col(f"_parts_{c}")

    def project(texts: pd.Series) -> pd.Series:
        return pd.Series(list(tfidf(texts.tolist(), idf, e) @ v))

    strings = df.select(F.col(c).alias(f"_text_{c}")).filter(F.col(f"_text_{c}").isNotNull()).distinct()
    table = strings.withColumn(f"_parts_{c}", F.pandas_udf(project, "array<double>")(f"_text_{c}"))
    return df.join(table, df[c] == table[f"_text_{c}"], "left"), F.col(f"_parts_{c}")


def route(df: DataFrame, columns: list[str], threshold: int = 40, n_components: int = 5) -> list[dict]:
    """The parts of an automatic table encoder, by type and number of distinct values."""
    kinds = dict(df.dtypes)
    text = [c for c in columns if kinds[c] == "string"]
    distinct = df.agg(*[F.approx_count_distinct(c).alias(c) for c in text]).first().asDict() if text else {}
    numeric = [c for c in columns if kinds[c] in ("int", "bigint", "double", "float") or kinds[c].startswith("decimal")]
    dates = [c for c in columns if kinds[c].startswith("timestamp") or kinds[c] == "date"]
    low, high = [c for c in text if distinct[c] <= threshold], [c for c in text if distinct[c] > threshold]
    parts = [("numeric", numeric, {}), ("onehot", low, {}), ("text", high, {"n_components": n_components}), ("dates", dates, {})]
    return [{"kind": k, "cols": cols} | more for k, cols, more in parts if cols]


#: Categories whose sums an interpreted apply holds in every worker.
ROW_CATEGORIES = 100_000


def apply_rows(df: DataFrame, encoders: list[dict], states: dict[str, dict], carry: list[str], train: str) -> tuple[DataFrame, list[str]]:
    """The interpreted form of ``apply_all``: Python computes every feature from the raw values.

    A step's function is called once for each distinct input of an Arrow batch; numbers are taken as arrays.
    """
    steps, names, inputs = [], [], []  # a step: places of its inputs (-1 is whether a row trains), its features, its function
    flags: set[str] = set()

    def need(column: str) -> int:
        if column not in inputs:
            inputs.append(column)
        return inputs.index(column)

    def step(at: list[int], own: list[str], fn: Callable) -> None:
        steps.append((at, len(own), fn))
        names.extend(own)

    for e in encoders:
        state = states[key_of(e)]
        if "error" in state:
            raise state["error"]
        for c in e["cols"]:
            at = need(c)
            if e["kind"] == "numeric":
                step([at], [f"f_{c}"], state[c])
                if e.get("indicator"):
                    step([at], [f"f_{c}_missing"], lambda v: [float(v is None)])
            elif e["kind"] == "onehot":
                kept, rare = state[c]
                kept = kept[1:] if e.get("drop_first", True) else kept
                own = [f"f_{c}_{k}" for k in range(len(kept))] + ([f"f_{c}_rare"] if rare else [])
                flags |= set(own)
                step([at], own, lambda v, kept=kept, rare=rare: row_onehot(v, kept, rare))
            elif e["kind"] == "dates":
                step([at], [f"f_{c}_{k}" for k in date_parts(c)], row_dates)
            elif e["kind"] == "target":
                fold = need(e["fold"]) if e.get("fold") else None
                found = state[c]["sums"].limit(ROW_CATEGORIES + 1).collect()
                if len(found) > ROW_CATEGORIES:
                    raise MemoryError(f"{c} has too many categories for a worker's table")
                sums = {(x["v"], x["fold"] if fold is not None else None): (x["s"] or 0.0, x["n"]) for x in found}
                whole: dict = {}
                for (v, _), (total, n) in sums.items():
                    a, b = whole.get(v, (0.0, 0))
                    whole[v] = (a + total, b + n)
                more = (float(e.get("smoothing", 10.0)), state[c]["total"], state[c]["folds"])
                if fold is None:
                    step([at, -1], [f"f_{c}_mean"], lambda v, t, sums=sums, whole=whole, more=more: [row_target(v, None, t, sums, whole, *more)])
                else:
                    step([at, fold, -1], [f"f_{c}_mean"], lambda v, f, t, sums=sums, whole=whole, more=more: [row_target(v, f, t, sums, whole, *more)])
            elif e["kind"] == "text":
                idf, v = state[c]["idf"], state[c]["v"]
                step([at], [f"f_{c}_part{k}" for k in range(v.shape[1])], lambda t, idf=idf, v=v, e=e: (tfidf([t], idf, e) @ v)[0].tolist())

    n_carry = len(carry)
    told = df.select(*carry, *[F.col(c).alias(f"_in{k}") for k, c in enumerate(inputs)], F.coalesce(F.expr(train), F.lit(False)).alias("_train"))
    schema = StructType([*told.schema.fields[:n_carry], *[StructField(n, DoubleType()) for n in names]])

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            columns = batch.columns
            raw, out = columns[n_carry:], columns[:n_carry]
            for at, width, fn in steps:
                own = [raw[k] for k in at]
                out += [row_numbers(own[0], *fn)] if isinstance(fn, tuple) else row_features(own, width, fn)
            yield pa.RecordBatch.from_arrays(out, [*batch.schema.names[:n_carry], *names])

    made = told.mapInArrow(features, schema)
    return made.select(*[F.col(f"`{c}`").alias(c, metadata={FLAG: True}) if c in flags else F.col(f"`{c}`") for c in made.columns]), names


def row_numbers(values: pa.Array, value: float, mean: float, std: float) -> pa.Array:
    x = values.cast(pa.float64())
    if x.null_count:
        x = x.fill_null(value)
    return pa.array((x.to_numpy(zero_copy_only=False) - mean) / std)


def row_features(inputs: list[pa.Array], width: int, fn: Callable) -> list[pa.Array]:
    """Features by column: the function's for the distinct inputs, taken by row."""
    coded = [a.dictionary_encode(null_encoding="encode") for a in inputs]
    values = [c.dictionary.to_pylist() for c in coded]
    at = np.zeros(len(inputs[0]), np.int64)
    for c in coded:
        at = at * max(1, len(c.dictionary)) + c.indices.to_numpy(zero_copy_only=False)
    distinct, taken = np.unique(at, return_inverse=True)
    rows = []
    for d in distinct.tolist():
        own = []
        for v in reversed(values):
            d, k = divmod(d, max(1, len(v)))
            own.append(v[k])
        rows.append(fn(*reversed(own)))
    return [pa.array([r[k] for r in rows], pa.float64()).take(pa.array(taken)) for k in range(width)]


def row_onehot(value: object, kept: list[str], rare: list[str]) -> list[float]:
    text = None if value is None else str(value).strip(" ")
    if text is not None and text.lower() in NULL_TOKENS:
        text = None
    return [float(text == v) for v in kept] + ([float(text in rare)] if rare else [])


def row_dates(value) -> list[float | None]:
    if value is None:
        return [None] * 5
    day = value.date() if hasattr(value, "date") else value
    return [float(x) for x in (day.year, day.month, day.day, day.isoweekday() % 7 + 1, day.toordinal() - 719_163)]


def row_target(value, fold, in_train: bool, sums: dict, whole: dict, m: float, total: tuple, folds: dict) -> float:
    s, n = whole.get(None if value is None else str(value), (0.0, 0))
    mean = total[0] / total[1] if total[1] else 0.0
    if in_train and folds:
        fs, fn = folds.get(fold, (0.0, 0))
        own_s, own_n = sums.get((None if value is None else str(value), fold), (0.0, 0))
        s, n = s - own_s, n - own_n
        if fold in folds:
            mean = (total[0] - fs) / (total[1] - fn) if total[1] > fn else mean
    if m:
        return (s + m * mean) / (n + m)
    return s / n if n else mean


def table_report(df: DataFrame, drop_null_fraction: float = 1.0, id_share: float = 0.95) -> dict[str, str]:
    """What to do with each column, from one aggregate: keep, drop (empty, constant or an identifier) or cast.

    An identifier is a text column with about as many distinct values as rows;
    a text column whose values are all numbers is to be cast.
    """
    aggs = [F.count(F.lit(1)).alias("rows")]
    kinds = dict(df.dtypes)
    flat = [c for c in df.columns if not kinds[c].startswith(("array", "map", "struct"))]
    for k, c in enumerate(flat):
        v = cleaned(F.col(f"`{c}`")) if kinds[c] == "string" else F.col(f"`{c}`")
        aggs += [F.count(v).alias(f"n{k}"), F.approx_count_distinct(v, 0.02).alias(f"d{k}"), F.min(v).eqNullSafe(F.max(v)).alias(f"c{k}")]
        if kinds[c] == "string":
            aggs.append(F.count_if(v.isNotNull() & F.expr(f"try_cast(trim(`{c}`) AS DOUBLE)").isNull()).alias(f"t{k}"))
    found = df.agg(*aggs).first().asDict()
    out, rows = {c: "keep" for c in df.columns}, found["rows"]
    for k, c in enumerate(flat):
        if rows and rows - found[f"n{k}"] >= drop_null_fraction * rows:
            out[c] = "drop: empty"
        elif rows and found[f"c{k}"] and found[f"n{k}"] == rows:
            out[c] = "drop: constant"
        elif kinds[c] == "string" and found[f"t{k}"] == 0 and found[f"n{k}"]:
            out[c] = "cast: double"
        elif kinds[c] == "string" and rows > 20 and found[f"d{k}"] >= id_share * rows:
            out[c] = "drop: identifier"
    return out


def clean_table(df: DataFrame, report: dict[str, str] | None = None, keep: tuple[str, ...] = ()) -> DataFrame:
    """Columns as the report has them; texts trimmed, null-like ones null."""
    report, kinds, out = report or table_report(df), dict(df.dtypes), []
    for c in df.columns:
        told = "keep" if c in keep else report[c]
        if told.startswith("drop"):
            continue
        v = cleaned(F.col(f"`{c}`")) if kinds[c] == "string" else F.col(f"`{c}`")
        out.append((F.expr(f"try_cast(trim(`{c}`) AS DOUBLE)") if told.startswith("cast") else v).alias(c))
    return df.select(*out)


def onehot_sparse(df: DataFrame, column: str, out: str) -> DataFrame:
    """One-hot as a sparse vector, for more categories than columns are made of; unseen and missing ones have no entry."""
    from pyspark.ml.feature import OneHotEncoder, StringIndexer

    text = df.withColumn(f"{out}_text", cleaned(F.col(column).cast("string")))
    indexed = StringIndexer(inputCol=f"{out}_text", outputCol=f"{out}_index", handleInvalid="keep", stringOrderType="alphabetAsc").fit(text).transform(text)
    encoder = OneHotEncoder(inputCols=[f"{out}_index"], outputCols=[out], dropLast=True, handleInvalid="keep").fit(indexed)
    return encoder.transform(indexed).drop(f"{out}_text", f"{out}_index")
