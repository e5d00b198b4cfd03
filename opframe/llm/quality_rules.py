"""Quality rules by robust multivariate outliers (operator 4), in DataFrame functions only.

Every text gives a vector of statistics on transformed scales. For each language and source,
for each language and for all texts, the minimum-covariance-determinant estimate of centre and
scatter is found by concentration steps: distances to the current estimate, the h rows of
least distance (by an approximate quantile, so no group is sorted in one task), mean and
covariance of those. Two starts run side by side and the one of the lesser determinant wins.
A text is judged by the finest of its three groups that has enough rows and is rejected if its
Mahalanobis distance is over the cut-off. All steps are aggregations over a table of
statistics; texts are read once.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise
from .graph import maybe_broadcast

SPACE = r"[\x20\x09-\x0D]+"
SYMBOLS = r"[^#*$%&|<>]+"
#: Names of the vector's parts and the least standard deviation that counts for each (its share of the scale that clean text varies by anyway).
FEATURES = {"f_words": 0.5, "f_word_len": 0.08, "f_symbols": 0.05, "f_dup_lines": 0.15, "f_repeat": 0.15, "f_capitals": 0.05, "f_marks": 0.05}
#: Share of rows that a concentration step keeps, steps, rows a group needs, and the cut-off (standard deviations of each of as many parts).
SUPPORT, STEPS, LEAST_ROWS, CUTOFF = 0.75, 3, 200, 6.0


def _let(value: Column, body) -> Column:
    """``body`` of a value that is computed once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _covered(words: Column, width: int) -> Column:
    """Words in windows of ``width`` words that the text has twice or more."""
    n = F.size(words)
    hashes = F.transform(F.sequence(F.lit(1), n - width + 1), lambda i: F.xxhash64(F.slice(words, i, width)))

    def repeated(h: Column) -> Column:
        pairs = F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("at"))))

        def spots(s: Column) -> Column:
            m = F.size(s)
            twice = F.filter(
                s,
                lambda x, i: ((i > 0) & (F.get(s, i - 1)["h"] == x["h"])) | ((i < m - 1) & (F.get(s, i + 1)["h"] == x["h"])),
            )
            at = F.sort_array(F.transform(twice, lambda x: x["at"]))
            return _let(
                at,
                lambda p: F.aggregate(
                    F.zip_with(p, F.slice(p, 2, F.greatest(F.size(p), F.lit(1))), lambda a, b: F.coalesce(F.least(b - a, F.lit(width)), F.lit(width))),
                    F.lit(0),
                    lambda acc, x: acc + x,
                ),
            )

        return F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(_let(pairs, spots))

    return F.when(n < width + 1, F.lit(0)).otherwise(_let(hashes, repeated)).cast("long")


def statistics(docs: DataFrame) -> DataFrame:
    """Base statistics of every whole text, lang and source (null: empty), and the transformed vector.

    Words are runs of characters other than space and 0x09-0x0D; a null or empty text has none
    and all its statistics are zero. Computed within a row: nothing is shuffled.
    """
    text = F.coalesce("text", F.lit(""))
    split = docs.select(
        "doc_id",
        F.coalesce(docs["lang"].cast("string"), F.lit("")).alias("lang"),
        F.coalesce(docs["source"].cast("string"), F.lit("")).alias("source"),
        text.alias("text"),
    )
    has_word = r"[^\x20\x09-\x0D]"
    words = F.filter(F.split("text", SPACE), lambda w: w != "")
    lines = F.filter(F.split("text", "\n"), lambda x: x.rlike(has_word))
    # one array per row holds what later columns need; bound once by transform over a single-element array
    row = F.transform(
        F.array(F.struct(words.alias("w"), lines.alias("l"))),
        lambda s: F.struct(
            F.size(s["w"]).cast("long").alias("n_words"),
            F.length(F.array_join(s["w"], "")).cast("long").alias("word_chars"),
            F.size(s["l"]).cast("long").alias("n_lines"),
            (F.size(s["l"]) - F.size(F.array_distinct(s["l"]))).cast("long").alias("n_dup_lines"),
            _covered(s["w"], 8).alias("n_repeat_words"),
        ),
    )
    out = split.select(
        "doc_id",
        "lang",
        "source",
        F.explode(row).alias("s"),
        F.length(F.regexp_replace("text", SYMBOLS, "")).cast("long").alias("n_symbols"),
        F.length(F.regexp_replace("text", r"[^\p{Lu}]+", "")).cast("long").alias("n_capitals"),
        F.length(F.regexp_replace("text", r"[^!?=~^_+@\\/\[\]{}]+", "")).cast("long").alias("n_marks"),
    ).select("doc_id", "lang", "source", "s.*", "n_symbols", "n_capitals", "n_marks")
    chars, n = F.greatest("word_chars", F.lit(1)), F.greatest("n_words", F.lit(1))
    return out.withColumns(
        {
            "f_words": F.log1p("n_words"),
            "f_word_len": F.log1p(F.col("word_chars") / n),
            "f_symbols": F.sqrt(F.col("n_symbols") / chars),
            "f_dup_lines": F.sqrt(F.col("n_dup_lines") / F.greatest("n_lines", F.lit(1))),
            "f_repeat": F.sqrt(F.col("n_repeat_words") / n),
            "f_capitals": F.sqrt(F.col("n_capitals") / chars),
            "f_marks": F.sqrt(F.col("n_marks") / chars),
        }
    )


def _inverse_factor(cov: dict[tuple[int, int], Column], p: int) -> list[tuple[str, Column]]:
    """Named columns, each from earlier ones, of the Cholesky factor l and of m = its inverse."""
    out: list[tuple[str, Column]] = []
    for j in range(p):
        for i in range(j, p):
            s = cov[i, j]
            for k in range(j):
                s = s - F.col(f"l{i}_{k}") * F.col(f"l{j}_{k}")
            out.append((f"l{i}_{j}", F.sqrt(F.greatest(s, F.lit(1e-9))) if i == j else s / F.col(f"l{j}_{j}")))
    for j in range(p):
        out.append((f"m{j}_{j}", 1 / F.col(f"l{j}_{j}")))
        for i in range(j + 1, p):
            s = F.lit(0.0)
            for k in range(j, i):
                s = s - F.col(f"l{i}_{k}") * F.col(f"m{k}_{j}")
            out.append((f"m{i}_{j}", s / F.col(f"l{i}_{i}")))
    return out


def _factored(moments: DataFrame, tag: str) -> DataFrame:
    """Moments to (group, centre, inverse factor, log determinant); floors keep constant parts from being singular."""
    names, p = list(FEATURES), len(FEATURES)
    cov = {}
    for i in range(p):
        for j in range(i + 1):
            c = F.coalesce(F.col(f"{tag}c{i}_{j}"), F.lit(0.0))
            cov[i, j] = c + F.lit(FEATURES[names[i]] ** 2) if i == j else c
    out = moments
    for name, column in _inverse_factor(cov, p):
        out = out.withColumn(name, column)
    logdet = sum((F.log(F.col(f"l{i}_{i}")) for i in range(1, p)), F.log("l0_0"))
    return out.withColumn(f"{tag}det", logdet).select(
        "g",
        *[c for c in moments.columns if c != "g"],
        F.array(*[F.col(f"{tag}u{i}") for i in range(p)]).alias(f"{tag}mu"),
        F.array(*[F.array(*[F.col(f"m{i}_{j}") for j in range(i + 1)]) for i in range(p)]).alias(f"{tag}m"),
        f"{tag}det",
    )


def _distance(tag: str) -> Column:
    """Squared Mahalanobis distance of the row's vector under the estimate ``tag``."""
    total = F.lit(0.0)
    for i in range(len(FEATURES)):
        y = F.lit(0.0)
        for j, f in enumerate(list(FEATURES)[: i + 1]):
            y = y + F.col(f"{tag}m")[i][j] * (F.col(f) - F.col(f"{tag}mu")[j])
        total = total + y * y
    return total


def _moments(rows: DataFrame, picks: dict[str, Column]) -> DataFrame:
    """Means and covariances of each group over the rows that each pick keeps."""
    aggs, names = [], list(FEATURES)
    for tag, keep in picks.items():
        for i, f in enumerate(names):
            aggs.append(F.avg(F.when(keep, F.col(f))).alias(f"{tag}u{i}"))
            for j in range(i + 1):
                aggs.append(F.covar_pop(F.when(keep, F.col(f)), F.when(keep, F.col(names[j]))).alias(f"{tag}c{i}_{j}"))
    return rows.groupBy("g").agg(*aggs)


def estimates(stats: DataFrame) -> DataFrame:
    """(g, n, mu, m): robust centre and inverse Cholesky factor of each group of ``stats``.

    Groups are [lang, source], [lang] and []; ``stats`` needs lang, source and the vector.
    """
    rows = materialise(
        stats.select(F.explode(F.array(F.array("lang", "source"), F.array("lang"), F.array().cast("array<string>"))).alias("g"), *FEATURES), "vectors"
    )
    names = list(FEATURES)
    medians = [F.percentile_approx(f, 0.5).alias(f"a{i}") for i, f in enumerate(names)]
    spreads = [F.percentile_approx(f, F.array(F.lit(0.25), F.lit(0.75))).alias(f"q{i}") for i, f in enumerate(names)]
    start = rows.groupBy("g").agg(F.count(F.lit(1)).alias("n"), *medians, *spreads).where(F.col("n") >= LEAST_ROWS)
    p = len(names)
    start = start.select(
        "g",
        "n",
        *[F.col(f"a{i}").alias(f"Au{i}") for i in range(p)],
        *[(F.pow((F.col(f"q{i}")[1] - F.col(f"q{i}")[0]) / 1.349, 2) if i == j else F.lit(0.0)).alias(f"Ac{i}_{j}") for i in range(p) for j in range(i + 1)],
    )
    start = materialise(start, "mcd-start")
    n_groups = start.count()
    sizes = start.select("g", "n")
    whole = _moments(rows, {"B": F.lit(True)})
    now = materialise(
        _factored(start, "A").select("g", "Amu", "Am", "Adet").join(_factored(whole.join(sizes, "g", "left_semi"), "B").select("g", "Bmu", "Bm", "Bdet"), "g"), "mcd"
    )
    for _ in range(STEPS):
        near = rows.join(maybe_broadcast(now, n_groups), "g").select("g", *FEATURES, _distance("A").alias("dA"), _distance("B").alias("dB"))
        cut = near.groupBy("g").agg(*[F.percentile_approx(f"d{t}", SUPPORT, 2000).alias(f"h{t}") for t in "AB"])
        cut = materialise(cut, "mcd-cut")
        kept = near.join(maybe_broadcast(cut, n_groups), "g")
        moments = materialise(_moments(kept, {t: F.col(f"d{t}") <= F.col(f"h{t}") for t in "AB"}), "mcd-moments")
        now = materialise(
            _factored(moments, "A").select("g", "Amu", "Am", "Adet").join(_factored(moments, "B").select("g", "Bmu", "Bm", "Bdet"), "g"), "mcd"
        )
    first = F.col("Adet") <= F.col("Bdet")
    best = now.join(sizes, "g").select("g", "n", F.when(first, F.col("Amu")).otherwise(F.col("Bmu")).alias("mu"), F.when(first, F.col("Am")).otherwise(F.col("Bm")).alias("m"))
    return materialise(best, "mcd-best")


def judge(docs: DataFrame) -> DataFrame:
    """Base statistics, base_failed, distance, level and kept of every row of ``docs``.

    ``docs`` has doc_id, text, lang, source; other columns are ignored. Estimates are made from
    rows that pass the base rules. Null languages and sources are groups of their own; where
    even all rows together are too few for an estimate (LEAST_ROWS), the base rules decide
    alone. level is 3 for language and source, 2 for language, 1 for all rows, 0 for none.
    """
    stats = statistics(docs).withColumn(
        "base_failed", (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    )
    stats = materialise(stats, "statistics")
    best = estimates(stats.where("not base_failed"))
    n = best.count()
    out = stats
    for level, key in ((3, F.array("lang", "source")), (2, F.array("lang")), (1, F.array().cast("array<string>"))):
        side = best.where(F.size("g") == level - 1).select(F.col("g").alias("__g"), F.struct("mu", "m").alias(f"e{level}"))
        out = out.join(maybe_broadcast(side, n), key == F.col("__g"), "left").drop("__g")
    out = out.withColumn("e", F.coalesce("e3", "e2", "e1")).withColumns(
        {"mu": F.col("e.mu"), "m": F.col("e.m"), "level": F.when(F.col("e3").isNotNull(), 3).when(F.col("e2").isNotNull(), 2).when(F.col("e1").isNotNull(), 1).otherwise(0)}
    )
    out = out.withColumn("distance", F.sqrt(_distance(""))).drop("e", "e1", "e2", "e3", "mu", "m")
    limit = CUTOFF
    return out.withColumn("kept", ~F.col("base_failed") & F.coalesce(F.col("distance") <= limit, F.lit(True)))


def query(spark, sf_dir: str) -> DataFrame:
    """The contract's columns for ``documents``, with the distance and the level that judged it."""
    out = judge(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "distance", "level")
