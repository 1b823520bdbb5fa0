"""Quality rules: robust multivariate outliers by minimum-covariance-determinant estimates.

Each document becomes a vector of transformed text statistics. For every language and source, and for all
documents together, the location and scatter of the central half are found by concentration steps: the documents
of least Mahalanobis distance are kept and the moments are taken anew. Three starts - medians and deviations, the
scatter of squashed coordinates, the scatter of spatial signs - take two steps each; the one of least determinant
goes on until its determinant falls no more. The squared floors are added to every scatter, under which a step
never raises the determinant. Everything is DataFrame operations: moments and quantiles are partial aggregates, so
a group of any size spreads over tasks, and documents meet their group's estimates by a broadcast of checked size.

Defined results: a null or wordless text has zero counts and fails the base rule. A group with fewer than
``min_group`` documents that pass the base rule takes the estimates of all documents; if those are too few as
well, the base rule alone decides. Null lang or source is a group of its own. Repeated rows are judged alike.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from starfold.llm.shared import discard, stored

#: Least spread of each feature, in its own unit. Length and word length only have a numerical guard. The
#: other three are zero in most clean texts, so that half of them has no spread at all; there one event (a symbol in 250
#: characters, a repeated line, a repeated window in 200 words) is about two spreads and no outlier by itself.
FLOORS = {"f_len": 0.05, "f_word": 0.02, "f_symbol": 0.03, "f_lines": 0.08, "f_repeat": 0.08}
#: Median of the sum of so many squared normal coordinates, and the 0.999 quantile of five.
MEDIANS, CUTOFF = (0.0, 0.455, 1.386, 2.366, 3.357, 4.351), 20.515
FEATURES = list(FLOORS)
N = len(FEATURES)
LOWER = [(i, j) for i in range(N) for j in range(i + 1)]
SPACE = " \t\n\x0b\x0c\r"
#: Key of the estimates of all documents; the key of a group starts with another sign.
ALL = "*"
#: Most rows of estimates (of about 250 bytes, three a group) that are sent to all tasks; more are met by a salted join.
MOST_SENT, SALTS = 50_000, 16
#: A determinant that falls by less, in its logarithm, is at rest.
REST = 1e-2


def with_statistics(docs: DataFrame, text: str = "text") -> DataFrame:
    """Adds n_words, word_chars, n_symbols, n_dup_lines and n_repeat_words of the whole text."""
    t = F.coalesce(F.col(text), F.lit(""))
    trimmed = F.trim(t, F.lit(SPACE))
    words = F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, "[ \\t\\n\\x0B\\f\\r]+"))
    lines = F.filter(F.split(t, "\n"), lambda x: x.rlike("[^ \\t\\n\\x0B\\f\\r]"))
    base = docs.withColumns({
        "_w": words,
        "_lines": lines,
        "n_symbols": F.length(F.regexp_replace(t, "[^#*$%&|<>]+", "")).cast("long"),
    })
    n = F.size("_w")
    grams = F.when(n < 3, F.array().cast("array<bigint>")).otherwise(
        F.zip_with(
            F.zip_with(F.slice("_w", 1, n - 2), F.slice("_w", 2, n - 2), lambda a, b: F.struct(a.alias("a"), b.alias("b"))),
            F.slice("_w", 3, n - 2),
            lambda ab, c: F.xxhash64(ab["a"], ab["b"], c),
        )
    )
    base = base.withColumns({
        "n_words": n.cast("long"),
        "word_chars": F.length(F.array_join("_w", "")).cast("long"),
        "n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"),
        "_g": grams,
    }).drop("_w", "_lines")
    # Only texts with a repeated window are sorted: equal windows meet there, and their places are marked.
    repeats = F.size("_g") != F.size(F.array_distinct("_g"))
    base = base.withColumn("_s", F.when(repeats, F.sort_array(F.transform("_g", lambda x, i: F.struct(x.alias("h"), i.alias("i"))))))
    size = F.size("_s")
    base = base.withColumn("_p", F.sort_array(F.transform(
        F.filter(
            F.zip_with(F.sequence(F.lit(1), size), "_s", lambda k, s: F.struct(k.alias("k"), s["h"].alias("h"), s["i"].alias("i"))),
            lambda x: ((x["k"] > 1) & (F.get("_s", x["k"] - 2)["h"] == x["h"])) | ((x["k"] < size) & (F.get("_s", x["k"])["h"] == x["h"])),
        ),
        lambda x: x["i"],
    )))
    many = F.size("_p")
    covered = F.aggregate(
        F.zip_with(F.slice("_p", 1, many - 1), F.slice("_p", 2, many - 1), lambda a, b: F.least(b - a, F.lit(3))),
        F.lit(0), lambda acc, x: acc + x,
    ) + 3
    return base.withColumn("n_repeat_words", F.when(repeats, covered).otherwise(0).cast("long")).drop("_g", "_s", "_p")


def _features() -> dict[str, Column]:
    n = F.greatest(F.col("n_words"), F.lit(1)).cast("double")
    return {
        "f_len": F.log1p(F.col("n_words").cast("double")),
        "f_word": F.col("word_chars") / n,
        "f_symbol": F.sqrt(F.col("n_symbols") / F.greatest(F.col("word_chars"), F.lit(1))),
        "f_lines": F.log1p(F.col("n_dup_lines").cast("double")) * 0.25,
        "f_repeat": F.sqrt(F.col("n_repeat_words") / n),
    }


def _with_distance(df: DataFrame) -> DataFrame:
    """Squared Mahalanobis distance, one whitened coordinate a step so that expressions stay small."""
    for i, c in enumerate(FEATURES):
        v = F.col(c) - F.col(f"m_{c}")
        for j in range(i):
            v = v - F.col(f"l_{i}_{j}") * F.col(f"z_{j}")
        df = df.withColumn(f"z_{i}", v / F.col(f"l_{i}_{i}"))
    total = sum((F.col(f"z_{i}") * F.col(f"z_{i}") for i in range(1, N)), F.col("z_0") * F.col("z_0"))
    return df.withColumn("d2", total).drop(*[f"z_{i}" for i in range(N)])


def _factor(moments: DataFrame, keep: list[str]) -> DataFrame:
    """``keep``, m_*, the Cholesky factor l_*_* of the scatter c_*_* with the squared floors on its diagonal, and its log determinant."""
    df = moments
    for j in range(N):
        floor = FLOORS[FEATURES[j]] ** 2
        diag = F.col(f"c_{j}_{j}") + floor
        for k in range(j):
            diag = diag - F.col(f"l_{j}_{k}") * F.col(f"l_{j}_{k}")
        # The sum of a scatter and the floors cannot be less than the floors but by rounding.
        df = df.withColumn(f"l_{j}_{j}", F.sqrt(F.greatest(diag, F.lit(floor))))
        for i in range(j + 1, N):
            off = F.col(f"c_{i}_{j}")
            for k in range(j):
                off = off - F.col(f"l_{i}_{k}") * F.col(f"l_{j}_{k}")
            df = df.withColumn(f"l_{i}_{j}", off / F.col(f"l_{j}_{j}"))
    logdet = sum((2 * F.log(f"l_{j}_{j}") for j in range(1, N)), 2 * F.log("l_0_0"))
    return df.select(*keep, *[f"m_{c}" for c in FEATURES], *[f"l_{i}_{j}" for i, j in LOWER], logdet.alias("logdet"))


def _meet(rows: DataFrame, small: DataFrame, sent: bool, key: str = "grp", how: str = "inner") -> DataFrame:
    """``rows`` with the row of ``small`` of their key: by broadcast if it is ``sent``, else by a join of which a hot key is dealt over ``SALTS`` tasks."""
    if sent:
        return rows.join(F.broadcast(small), key, how)
    dealt = rows.withColumn("_salt", F.pmod(F.xxhash64(*FEATURES), F.lit(SALTS)))
    copies = small.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    return dealt.join(copies, [key, "_salt"], how).drop("_salt")


def _starts(points: DataFrame) -> tuple[DataFrame, DataFrame, bool]:
    """(grp, n) of all groups, the first estimates (grp, start, m_*, l_*_*, logdet) from medians, squashed coordinates and spatial signs, and whether these are few enough to be sent."""
    middle = stored(points.groupBy("grp").agg(
        F.count("*").alias("n"), *[F.percentile_approx(c, F.lit(0.5), F.lit(1000)).alias(f"m_{c}") for c in FEATURES],
    ))
    sent = 3 * middle.count() <= MOST_SENT
    spread = _meet(points, middle, sent).groupBy("grp").agg(
        *[F.first(f"m_{c}").alias(f"m_{c}") for c in FEATURES],
        *[F.percentile_approx(F.abs(F.col(c) - F.col(f"m_{c}")), F.lit(0.5), F.lit(1000)).alias(f"s_{c}") for c in FEATURES],
    )
    scale = stored(spread.select("grp", *[f"m_{c}" for c in FEATURES], *[F.sqrt(F.pow(F.col(f"s_{c}") * 1.4826, 2) + FLOORS[c] ** 2).alias(f"s_{c}") for c in FEATURES]))
    near = _meet(points, scale, sent)
    z = [(F.col(c) - F.col(f"m_{c}")) / F.col(f"s_{c}") for c in FEATURES]
    near = near.select("grp", *[x.alias(f"z_{i}") for i, x in enumerate(z)])
    size = F.sqrt(sum((F.pow(f"z_{i}", 2) for i in range(1, N)), F.pow("z_0", 2)))
    near = near.withColumn("_size", F.greatest(size, F.lit(1e-12)))
    moments = near.groupBy("grp").agg(
        *[F.avg(F.tanh(f"z_{i}") * F.tanh(f"z_{j}")).alias(f"t_{i}_{j}") for i, j in LOWER],
        *[(N * F.avg(F.col(f"z_{i}") * F.col(f"z_{j}") / (F.col("_size") * F.col("_size")))).alias(f"u_{i}_{j}") for i, j in LOWER],
    )
    known = scale.join(moments, "grp")

    def start(k: int, entry) -> DataFrame:
        unit = lambda i, j: F.col(f"s_{FEATURES[i]}") * F.col(f"s_{FEATURES[j]}") * entry(i, j)
        return known.select("grp", F.lit(k).alias("start"), *[f"m_{c}" for c in FEATURES], *[unit(i, j).alias(f"c_{i}_{j}") for i, j in LOWER])

    every = start(0, lambda i, j: F.lit(float(i == j))).unionByName(start(1, lambda i, j: F.col(f"t_{i}_{j}"))).unionByName(start(2, lambda i, j: F.col(f"u_{i}_{j}")))
    models = stored(_factor(every, ["grp", "start"]))
    sizes = stored(middle.select("grp", "n"))
    for t in (middle, scale):
        discard(t)
    return sizes, models, sent


def _concentrate(points: DataFrame, models: DataFrame, sent: bool) -> DataFrame:
    """One concentration step of every (grp, start); ``fall`` is what the logarithm of its determinant lost."""
    cols = [c for c in models.columns if c != "fall"]
    half = _with_distance(_meet(points, models.select(*cols), sent)).groupBy("grp", "start").agg(F.percentile_approx("d2", F.lit(0.5), F.lit(1000)).alias("half"))
    bounded = stored(models.select(*cols).join(half, ["grp", "start"]))
    inner = _with_distance(_meet(points, bounded, sent)).where("d2 <= half")
    moments = inner.groupBy("grp", "start").agg(
        F.first("logdet").alias("before"), *[F.avg(c).alias(f"m_{c}") for c in FEATURES],
        *[F.covar_pop(FEATURES[i], FEATURES[j]).alias(f"c_{i}_{j}") for i, j in LOWER],
    )
    out = stored(_factor(moments, ["grp", "start", "before"]).withColumn("fall", F.col("before") - F.col("logdet")).drop("before"))
    discard(bounded)
    return out


def estimates(points: DataFrame, *, max_steps: int = 100) -> tuple[DataFrame, bool]:
    """For each grp of ``points`` (grp, features): n, location m_*, factor l_*_* of the scatter of its central half, and the median distance ``half``; and whether the table may be sent to all tasks."""
    sizes, models, sent = _starts(points)
    for _ in range(2):
        models, was = _concentrate(points, models, sent), models
        discard(was)
    best = [c for c in models.columns if c != "grp"]
    chosen = models.groupBy("grp").agg(F.min_by(F.struct(*best), F.struct("logdet", "start")).alias("b")).select("grp", "b.*")
    models, was = stored(chosen), models
    discard(was)
    settled = []
    for _ in range(max_steps):
        going = models.where(F.col("fall") > REST)
        settled.append(models.where(F.col("fall") <= REST))
        if going.isEmpty():
            break
        models = _concentrate(points, going, sent)
    else:
        settled.append(models)
    final = settled[0]
    for part in settled[1:]:
        final = final.unionByName(part)
    final = stored(final.drop("start", "logdet", "fall"))
    half = _with_distance(_meet(points, final, sent)).groupBy("grp").agg(F.percentile_approx("d2", F.lit(0.5), F.lit(1000)).alias("half"))
    return stored(final.join(half, "grp").join(sizes, "grp")), sent


def _judged(docs: DataFrame, id_col: str, text: str, groups: tuple[str, ...], min_words: int, min_group: int, cutoff: float, carry: bool) -> DataFrame:
    """Statistics and verdict of every row; with ``carry`` also the row itself, as the column ``row``."""
    name = F.concat_ws("\x1f", F.lit("="), *[F.coalesce(F.col(g).cast("string"), F.lit("\x00")) for g in groups if g in docs.columns])
    narrow = docs.select(*[F.struct("*").alias("row")] * carry, F.col(id_col).alias("doc_id"), F.col(text).alias("text"), name.alias("grp"))
    failed = (F.col("n_words") < min_words) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    rows = stored(with_statistics(narrow).drop("text").withColumn("base_failed", failed).withColumns(_features()))
    points = rows.where("not base_failed").select(F.explode(F.array("grp", F.lit(ALL))).alias("grp"), *FEATURES)
    found, sent = estimates(points)
    # A group that is too small takes the estimates of all documents; only these small tables meet here.
    key = F.when(F.col("n") >= min_group, F.col("grp")).otherwise(F.lit(ALL))
    named = found.where(F.col("grp") != ALL).select("grp", key.alias("from"))
    model = stored(named.join(found.where(F.col("n") >= min_group).drop("n").withColumnRenamed("grp", "from"), "from").drop("from"))
    both = _meet(rows, model, sent, how="left")
    free = sum(((F.col(f"l_{i}_{i}") > FLOORS[c] * 2**0.5).cast("int") for i, c in enumerate(FEATURES)), F.lit(0))
    median = F.element_at(F.array(*[F.lit(m) for m in MEDIANS]), free + 1)
    scaled = F.col("d2") / F.when(median > 0, F.greatest(F.col("half") / median, F.lit(1.0))).otherwise(1.0)
    both = _with_distance(both).withColumn("distance2", scaled)
    verdict = ~F.col("base_failed") & F.coalesce(F.col("distance2") <= cutoff, F.lit(True))
    return both.withColumn("kept", verdict)


def judge(
    docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", groups: tuple[str, ...] = ("lang", "source"),
    min_words: int = 50, min_group: int = 40, cutoff: float = CUTOFF,
) -> DataFrame:
    """doc_id, the base statistics, base_failed, distance2 (scaled) and kept for every row of ``docs``.

    ``cutoff`` bounds the squared distance after it is scaled so that the median equals that of normal coordinates,
    as many as vary above their floors; that makes up for the scatter being that of the central half.
    """
    return _judged(docs, id_col, text, groups, min_words, min_group, cutoff, False).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "distance2", "kept"
    )


def filter_documents(
    docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", groups: tuple[str, ...] = ("lang", "source"),
    min_words: int = 50, min_group: int = 40, cutoff: float = CUTOFF,
) -> DataFrame:
    """The rows of ``docs`` that are kept, with their own columns, each by its own text. Texts are never shuffled: a row stays beside its statistics."""
    return _judged(docs, id_col, text, groups, min_words, min_group, cutoff, True).where("kept").select("row.*")
