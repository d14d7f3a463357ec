"""Quality rules with risk-controlled thresholds, in DataFrame operations only.

Measures of each text are compared with cutoffs that labelled holdouts set. In every
stratum (language), the share of good documents that its rules reject together is at
most RISK with confidence: of a set of rules with their cutoffs, the exact binomial tail
P(X <= k; n, RISK), for k of n good rows rejected by any of them, must be at most
ERROR / strata. This is the one-sided exact (Clopper-Pearson) bound on the whole set, with
Bonferroni's correction over strata. So with probability 1 - ERROR at least, in every
stratum at most RISK of good documents are rejected by these rules. Without any false
rejection, n >= 217 does for four strata.

Sets are tried in a fixed sequence that the tested rows have no part in: one in
DESIGN_EACH of the good rows and all bad ones say which cutoffs there are, by LEVELS of
good rows lost, and in which order they join the set: by level, then by bad rows
rejected. Each set holds the one before, the first that fails ends the sequence, which
needs no further correction. Cutoffs that reject no bad row take no part. A stratum in
which no set passes has no cutoffs. Holdout rows are labelled rows with quality 0 or 1.

The cutoffs' table has a row per stratum; it is broadcast while there are at most
BROADCAST_STRATA, beyond that joined by shuffle with salted strata.

Edge cases: null text has no words: all measures are 0 and the base rule fails it; null
strata form one stratum, and strata without labelled rows have no cutoffs; long texts are
read whole; repeated ids are rated each, and a labelled id's copies all join the holdout;
without labels only the base rule rejects; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tidelabel.llm.common import documents, materialise

RISK, ERROR = 0.02, 0.05
#: One in DESIGN_EACH good rows sets the order of trial; cutoffs lose these shares of them at most.
DESIGN_EACH, LEVELS = 5, (0.0, 0.0025, 0.005, 0.01, 0.02)
BROADCAST_STRATA, SALTS = 10_000, 64
#: The base rule.
LEAST_WORDS, REPEAT_PERCENT, WINDOW = 10, 20, 5
WHITE = "[\\x20\\x09-\\x0D]+"
SYMBOLS = "[#*$%&|<>]"
#: Rules: a document is rejected whose measure is above the cutoff.
RULES = {
    "symbol_share": "n_symbols / greatest(word_chars, 1)",
    "dup_line_share": "n_dup_lines / greatest(n_lines, 1)",
    "repeat_share": "n_repeat_words / greatest(n_words, 1)",
    "long_words": "word_chars / greatest(n_words, 1)",
    "few_distinct": "1 - n_distinct / greatest(n_words, 1)",
}


def repeat_words(words: str, h: str) -> Column:
    """Words that lie in a window whose hash occurs twice or more in the array ``h`` of window hashes.

    Only texts with a repeated window go past the size comparison. The windows are
    sorted with their places, those equal to a neighbour kept, and the places sorted:
    each covers WINDOW words or as many as there are up to the next one.
    """
    return F.expr(f"""
        case when size(array_distinct({h})) = size({h}) then 0L else
        aggregate(
          transform(array(array_sort(transform({h}, (x, i) -> struct(x as x, i as i)), (a, b) -> case when a.x < b.x then -1 when a.x > b.x then 1 else a.i - b.i end)),
            s -> sort_array(transform(
              filter(sequence(0, size(s) - 1), j -> (j > 0 and s[j - 1].x = s[j].x) or (j < size(s) - 1 and s[j + 1].x = s[j].x)),
              j -> s[j].i)))[0],
          struct(0L as n, -{WINDOW} as last),
          (a, p) -> struct(a.n + least({WINDOW}, p - a.last) as n, p as last),
          a -> a.n) end""")


def measures(docs: DataFrame, stratum: str = "lang") -> DataFrame:
    """doc_id, stratum and the measures of each text."""
    words = "filter(split(text, '" + WHITE.replace("\\", "\\\\") + "'), w -> w <> '')"
    rows = docs.select("doc_id", F.coalesce(F.col(stratum).cast("string"), F.lit("")).alias("stratum"), F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.withColumn("words", F.expr(words)).withColumn("lines", F.expr("filter(split(text, '\\n'), l -> length(translate(l, ' \\t\\n\\u000b\\u000c\\r', '')) > 0)"))
    window = ", ".join(f"words[i + {j}]" for j in range(WINDOW))
    rows = rows.withColumn("h", F.expr(f"case when size(words) < {WINDOW} then array() else transform(sequence(0, size(words) - {WINDOW}), i -> xxhash64({window})) end"))
    return rows.select(
        "doc_id", "stratum", F.size("words").cast("long").alias("n_words"), F.expr("cast(length(array_join(words, '')) as long)").alias("word_chars"),
        F.expr(f"cast(regexp_count(text, '{SYMBOLS}') as long)").alias("n_symbols"), F.expr("cast(size(lines) - size(array_distinct(lines)) as long)").alias("n_dup_lines"),
        F.size("lines").cast("long").alias("n_lines"), F.expr("cast(size(array_distinct(words)) as long)").alias("n_distinct"), repeat_words("words", "h").alias("n_repeat_words"),
    )


def binomial_tail(k: str, n: str, p: float) -> Column:
    """P(X <= k) for X binomial(n, p), summed from X = k down in logarithms of ratios."""
    odds = p / (1 - p)
    # log P(X = k) by a sum of logs, then terms relative to it while going down
    log_pk = f"aggregate(sequence(1, cast({k} as int)), {n} * ln(1 - {p}), (a, i) -> a + ln(({n} - i + 1) * {odds} / i))"
    log_p0 = f"{n} * ln(1 - {p})"
    relative = f"aggregate(sequence(1, cast({k} as int)), struct(1D as s, 1D as t), (a, i) -> struct(a.s + a.t * ({k} - i + 1) / (({n} - {k} + i) * {odds}) as s, a.t * ({k} - i + 1) / (({n} - {k} + i) * {odds}) as t), a -> a.s)"
    return F.expr(f"case when {k} >= {n} then 1D when {k} = 0 then exp({log_p0}) when {k} > {n} * {p} then 1D else least(1D, exp({log_pk} + ln({relative}))) end")


def trials(design: DataFrame) -> DataFrame:
    """(stratum, items): the (rank, rule, cut) to try, in this order, from (stratum, quality, rules...)."""
    long = design.select("stratum", "quality", F.expr("stack({}, {}) as (rule, value)".format(len(RULES), ", ".join(f"'{r}', cast({e} as double)" for r, e in RULES.items()))))
    good = long.where("quality = 1").groupBy("stratum", "rule").agg(F.max("value").alias("most"), F.expr(f"percentile_approx(value, array({', '.join(str(1 - x) for x in LEVELS[1:])}), 10000)").alias("points"))
    bad = long.where("quality = 0").join(good, ["stratum", "rule"])
    # where no good row lies above, the cutoff is halfway to the next bad one
    next_bad = bad.where("value > most").groupBy("stratum", "rule").agg(F.min("value").alias("next"))
    halfway = F.expr("transform(concat(array((most + coalesce(next, most)) / 2), points), (c, i) -> struct(i as level, c as cut))")
    items = good.join(next_bad, ["stratum", "rule"], "left").select("stratum", "rule", F.explode(halfway).alias("x")).select("stratum", "rule", "x.*")
    gains = bad.select("stratum", "rule", "value").join(items, ["stratum", "rule"]).where("value > cut").groupBy("stratum", "rule", "level", "cut").agg(F.count("*").alias("gain"))
    ranked = gains.withColumn("rank", F.expr("row_number() over (partition by stratum order by level, gain desc, rule)"))
    return ranked.groupBy("stratum").agg(F.collect_list(F.struct("rank", "rule", "cut")).alias("items"))


def cutoffs(holdout: DataFrame, risk: float = RISK, error: float = ERROR) -> DataFrame:
    """(stratum, cuts): lowest admitted cutoff by rule, from (doc_id, stratum, quality, rules...)."""
    rows = holdout.withColumn("designs", F.pmod(F.xxhash64(*holdout.columns), F.lit(DESIGN_EACH)) == 0)
    items = materialise(trials(rows.where("quality = 0 or designs")), "quality-trials")
    value = " ".join(f"when '{r}' then cast({e} as double)" for r, e in RULES.items())
    # the first set that rejects a row; later ones do so too
    first = rows.where("quality = 1 and not designs").join(items, "stratum").select("stratum", F.expr(f"array_min(transform(filter(items, s -> case s.rule {value} end > s.cut), s -> s.rank))").alias("rank"))
    found = first.groupBy("stratum", "rank").agg(F.count("*").alias("n"))
    good = found.groupBy("stratum").agg(F.sum("n").alias("good"))
    tried = items.select("stratum", F.explode("items").alias("x")).select("stratum", "x.*").join(good, "stratum").join(found, ["stratum", "rank"], "left")
    tried = tried.withColumn("above", F.expr("coalesce(sum(n) over (partition by stratum order by rank), 0L)"))
    strata = holdout.agg(F.countDistinct("stratum").alias("strata"))
    admitted = tried.crossJoin(F.broadcast(strata)).withColumn("tail", binomial_tail("above", "good", risk)).where(f"tail <= {error} / strata")
    lowest = admitted.groupBy("stratum", "rule").agg(F.min("cut").alias("cut"))
    return lowest.groupBy("stratum").agg(*(F.max(F.when(F.col("rule") == r, F.col("cut"))).alias(f"cut_{r}") for r in RULES))


def judged(measured: DataFrame, cuts: DataFrame) -> DataFrame:
    """Measures with base_failed and kept."""
    if cuts.count() <= BROADCAST_STRATA:
        rows = measured.join(F.broadcast(cuts), "stratum", "left")
    else:
        salted = cuts.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        rows = measured.withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(SALTS)).cast("int")).join(salted, ["stratum", "salt"], "left").drop("salt")
    rejected = " or ".join(f"coalesce(cast({e} as double) > cut_{r}, false)" for r, e in RULES.items())
    base = f"(n_words < {LEAST_WORDS} or 100 * n_repeat_words > {REPEAT_PERCENT} * n_words)"
    return rows.withColumn("base_failed", F.expr(base)).withColumn("kept", F.expr(f"not base_failed and not ({rejected})"))


def quality_rules(docs: DataFrame, labels: DataFrame, stratum: str = "lang", risk: float = RISK, error: float = ERROR) -> DataFrame:
    """All measures and the verdict for each row of ``docs``; labels: (doc_id, quality)."""
    measured = materialise(measures(docs, stratum), "quality-measures")
    rated = measured.join(labels.where("quality in (0, 1)").select("doc_id", F.col("quality").cast("int").alias("quality")), "doc_id")
    # rows of the base rule are rejected anyway: the thresholds' risk is about the others
    base_kept = rated.where(f"n_words >= {LEAST_WORDS} and 100 * n_repeat_words <= {REPEAT_PERCENT} * n_words")
    cuts = materialise(cutoffs(base_kept, risk, error), "quality-cutoffs")
    return judged(measured, cuts)


def op8_risk_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = quality_rules(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return found.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")
