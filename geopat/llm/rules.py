"""Quality rules with adaptive thresholds; DataFrame functions only.

Statistics of each text are shares (symbols, capitals, exclamation and bar marks, repeated lines and
words, mean word length).  For every (lang, source) a mergeable quantile sketch of each
statistic is built: counts per bucket of fixed relative width, so sketches of parts add
up to the sketch of the whole, reruns agree, and a sketch has at most a few thousand
buckets.  A document fails a statistic that lies beyond the group's fence, median plus
`reach` times the upper half-spread.  A half-spread counts as `spread` at least, since that of a statistic
that most documents have at 0 is 0.  Groups of fewer than `least` documents take the
fences of their language, then of all documents; without any fence nothing lies beyond.

Null and empty texts have no words and fail the base rule.  Null lang or source are
groups of their own.  Repeated rows and ties are judged alike.  An empty table gives no
rows.  Other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import WORD, materialise, table, text_or_empty

RUN = 8
#: Statistic: (least half-spread, reach in half-spreads).
FENCES = {"symbol_share": (0.005, 6.0), "mark_share": (0.005, 6.0), "capital_share": (0.002, 6.0), "line_share": (0.03, 6.0), "repeat_share": (0.02, 6.0), "mean_word": (0.05, 6.0)}
GROWTH = 1.005
SMALLEST = 1e-3


def _let(value: Column, body) -> Column:
    """Bind a value once for use inside lambdas, where a repeated expression is computed per element."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _covered(hashes: Column) -> Column:
    """Words covered by windows whose hash is found twice or more."""

    def by_hash(pairs: Column) -> Column:
        n = F.size(pairs)
        same = lambda i, j: F.get(pairs, i)["h"] == F.get(pairs, j)["h"]
        twice = F.filter(pairs, lambda e, i: F.coalesce((i > 0) & same(i, i - 1), F.lit(False)) | F.coalesce((i + 1 < n) & same(i, i + 1), F.lit(False)))
        starts = F.array_sort(F.transform(twice, lambda e: e["i"]))
        start = F.struct(F.lit(-RUN).alias("last"), F.lit(0).alias("n"))
        step = lambda a, i: F.struct(i.cast("int").alias("last"), (a["n"] + F.least(F.lit(RUN), i - a["last"])).cast("int").alias("n"))
        return F.aggregate(starts, start, step)["n"]

    return _let(F.array_sort(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i")))), by_hash)


def base_columns(text: Column) -> Column:
    """Struct of n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words of a text."""
    lines = F.filter(F.split(text, "\n", -1), lambda line: F.length(F.translate(line, " \t\x0b\x0c\r", "")) > 0)

    def of_words(words: Column) -> Column:
        n = F.size(words)

        def of_hashes(h: Column) -> Column:
            windows = F.transform(F.sequence(F.lit(0), n - RUN), lambda i: F.xxhash64(*[F.get(h, i + k) for k in range(RUN)]))
            return _let(windows, lambda w: F.when(F.size(F.array_distinct(w)) == F.size(w), 0).otherwise(_covered(w)))

        repeated = F.when(n <= RUN, 0).otherwise(_let(F.transform(words, lambda w: F.xxhash64(w)), of_hashes))
        return F.struct(n.cast("long").alias("n_words"), repeated.cast("long").alias("n_repeat_words"))

    return F.struct(
        _let(F.regexp_extract_all(text, F.lit(f"({WORD})"), F.lit(1)), of_words).alias("words"),
        F.length(F.translate(text, " \t\n\x0b\x0c\r", "")).cast("long").alias("word_chars"),
        (F.length(text) - F.length(F.translate(text, "#*$%&|<>", ""))).cast("long").alias("n_symbols"),
        _let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"),
        F.size(lines).cast("long").alias("n_lines"),
        (F.length(text) - F.length(F.translate(text, "!#*$%&|<>", ""))).cast("long").alias("n_marks"),
        (F.length(text) - F.length(F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZÀÁÂÄÇÈÉÊËÍÎÏÑÓÔÖÙÚÛÜ", ""))).cast("long").alias("n_capitals"),
    )


def statistics(docs: DataFrame) -> DataFrame:
    found = docs.select("doc_id", "lang", "source", base_columns(text_or_empty()).alias("b"))
    chars, words = F.greatest(F.col("b.word_chars"), F.lit(1)), F.greatest(F.col("b.words.n_words"), F.lit(1))
    return found.select(
        "doc_id", "lang", "source", "b.words.n_words", "b.word_chars", "b.n_symbols", "b.n_dup_lines", "b.words.n_repeat_words",
        (F.col("b.n_symbols") / chars).alias("symbol_share"),
        (F.col("b.n_marks") / chars).alias("mark_share"),
        (F.col("b.n_capitals") / chars).alias("capital_share"),
        (F.col("b.n_dup_lines") / F.greatest(F.col("b.n_lines"), F.lit(1))).alias("line_share"),
        (F.col("b.words.n_repeat_words") / words).alias("repeat_share"),
        (F.col("b.word_chars") / words).alias("mean_word"),
    )


def _bucket(value: Column) -> Column:
    return F.when(value <= SMALLEST, 0).otherwise(F.ceil(F.log(value / SMALLEST) / F.log(F.lit(GROWTH)))).cast("int")


def _value(bucket: Column) -> Column:
    return F.when(bucket == 0, 0.0).otherwise(SMALLEST * F.pow(F.lit(GROWTH), bucket - F.lit(0.5)))


def sketches(stats: DataFrame, keys: list[str], names: list[str]) -> DataFrame:
    """Mergeable sketch rows (keys, stat, bucket, n)."""
    each = F.array(*[F.struct(F.lit(i).alias("stat"), _bucket(F.col(s)).alias("bucket")) for i, s in enumerate(names)])
    return stats.select(*keys, F.inline(each)).groupBy(*keys, "stat", "bucket").agg(F.count("*").alias("n"))


def quantiles(sketch: DataFrame, keys: list[str], shares: dict[str, float]) -> DataFrame:
    """(keys, stat, total, one column per share) from sketch rows."""
    of = Window.partitionBy(*keys, "stat")
    ranked = sketch.withColumns({"total": F.sum("n").over(of), "upto": F.sum("n").over(of.orderBy("bucket"))})
    at = [_value(F.min(F.when(F.col("upto") >= share * F.col("total"), F.col("bucket")))).alias(name) for name, share in shares.items()]
    return ranked.groupBy(*keys, "stat").agg(F.first("total").alias("total"), *at)


def fences(sketch: DataFrame, keys: list[str], name: str, limits: dict[str, tuple[float, float]] = FENCES) -> DataFrame:
    """(keys, total, <name> = array of upper fences by statistic)."""
    q = quantiles(sketch, keys, {"mid": 0.5, "high": 0.75})
    spread = F.get(F.array(*[F.lit(v[0]) for v in limits.values()]), F.col("stat"))
    reach = F.get(F.array(*[F.lit(v[1]) for v in limits.values()]), F.col("stat"))
    fence = F.col("mid") + reach * F.greatest(spread, F.col("high") - F.col("mid"))
    tidy = F.transform(F.array_sort(F.collect_list(F.struct("stat", fence.alias("fence")))), lambda x: x["fence"])
    return q.groupBy(*keys).agg(F.first("total").alias("total"), tidy.alias(name))


def judge(docs: DataFrame, limits: dict[str, tuple[float, float]] = FENCES, least: int = 200) -> DataFrame:
    """Statistics of every document with base_failed, failed (names of statistics beyond their fence) and kept."""
    stats = statistics(docs)
    names = list(limits)
    base_failed = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    held = materialise(stats.withColumn("base_failed", base_failed))
    fine = materialise(sketches(held.where("not base_failed"), ["lang", "source"], names))
    by_lang = fine.groupBy("lang", "stat", "bucket").agg(F.sum("n").alias("n"))
    overall = fine.groupBy("stat", "bucket").agg(F.sum("n").alias("n")).withColumn("one", F.lit(1))
    g1 = fences(fine, ["lang", "source"], "f1", limits).where(F.col("total") >= least).select(F.col("lang").alias("l1"), F.col("source").alias("s1"), "f1")
    g2 = fences(by_lang, ["lang"], "f2", limits).where(F.col("total") >= least).select(F.col("lang").alias("l2"), "f2")
    g3 = fences(overall, ["one"], "f3", limits).select("f3")
    groups = materialise(g1.coalesce(1))
    small = groups.count() < 100_000
    joined = (
        held.join(F.broadcast(groups) if small else groups, F.col("l1").eqNullSafe(F.col("lang")) & F.col("s1").eqNullSafe(F.col("source")), "left")
        .join(g2, F.col("l2").eqNullSafe(F.col("lang")), "left")
        .withColumn("one", F.lit(1))
        .join(F.broadcast(g3.withColumn("one", F.lit(1))), "one", "left")
    )
    fence = F.coalesce("f1", "f2", "f3", F.array(*[F.lit(float("inf")) for _ in limits]))
    beyond = F.array_compact(F.array(*[F.when(F.col(s) > F.get(F.col("fence"), F.lit(i)), F.lit(s)) for i, s in enumerate(names)]))
    return (
        joined.withColumn("fence", fence)
        .withColumn("failed", beyond)
        .withColumn("kept", ~F.col("base_failed") & (F.size("failed") == 0))
        .drop("l1", "s1", "f1", "l2", "f2", "f3", "one", "fence")
    )


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    names = ("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "failed")
    return judge(table(spark, sf_dir, "documents")).select(*names)
