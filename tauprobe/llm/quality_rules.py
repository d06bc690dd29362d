"""Quality rules with risk-controlled thresholds, in DataFrame functions only.

`features` counts words, symbols, repeated lines and repeated word windows of each text inside its row; nothing is shuffled.
`cutoffs` picks, for each stratum and rule, a cutoff from labelled rows such that the share of good documents that the
cutoff rejects is at most the rule's part of `Risk.alpha`, with confidence 1 - `Risk.delta` over all strata and rules
together. The labelled good rows of a stratum are the holdout: a cutoff may be used if the exact binomial probability of
so few rejections, were the true share at the limit, is at most delta over the number of tests (Bonferroni). Cutoffs are
tried from the most lenient one on and the search ends at the first that fails, so the many cutoffs of a test need no
further correction. Among those that may be used, the one with the most bad rows less `harm` times the good rows it
rejects is taken, if that is above zero. A stratum with too few labelled good rows for the bound has no cutoff: a cutoff
that holds for all rows together would promise nothing for that stratum.

Defined results: a null text has no words; empty texts fail the base rules; very long texts count whole; repeated rows
give repeated results; of a repeated label the lowest counts; null strata are a stratum of their own (the empty string);
without labels no rule has a cutoff; an empty table gives an empty table; only the named columns are read.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tauprobe.session import materialize

SPACE = r"[ \t-\r]"
SYMBOLS = "[#*$%&|<>]"


@dataclass(frozen=True)
class Risk:
    #: Share of good documents of a stratum that all rules together may reject.
    alpha: float = 0.02
    delta: float = 0.05
    harm: float = 3.0


#: Rule name to what it measures, in whole thousandths or hundredths; a document is rejected above the cutoff.
RULES: dict[str, str] = {
    "symbols": "1000 * n_symbols div greatest(word_chars, 1)",
    "lines": "1000 * n_dup_lines div greatest(n_lines, 1)",
    "repeats": "1000 * n_repeat_words div greatest(n_words, 1)",
    "long_words": "least(100 * word_chars div greatest(n_words, 1), 5000)",
    "short_words": "5000 - least(100 * word_chars div greatest(n_words, 1), 5000)",
}
BASE_FAILED = "n_words < 50 or 100 * n_repeat_words > 50 * n_words"


def words_of(text: Column) -> Column:
    trimmed = F.btrim(text, F.lit(" \t\n\x0b\f\r"))
    return F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, SPACE + "+"))


def _lines(text: Column) -> Column:
    return F.filter(F.split(text, "\n"), lambda line: line.rlike(r"[^ \t-\r]"))


def _window_keys() -> Column:
    """For each three-word window its hash, with the low bits replaced by its place."""
    def key(i):
        return F.xxhash64(F.col("words")[i], F.col("words")[i + 1], F.col("words")[i + 2]).bitwiseAND(F.bitwise_not("low")).bitwiseOR(i.cast("bigint"))

    places = F.sequence(F.lit(0), F.size("words") - 3)
    return F.when(F.size("words") >= 3, F.sort_array(F.transform(places, key))).otherwise(F.array().cast("array<bigint>"))


def _same_beside(array: str, part) -> Column:
    """The elements of a sorted array whose part equals that of the one before or after."""
    same = lambda x, k: F.coalesce(part(x) == part(F.get(F.col(array), k)), F.lit(False))
    return F.filter(F.col(array), lambda x, j: same(x, j - 1) | same(x, j + 1))


def features(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", stratum_col: str | None = "lang", key_col: str | None = None) -> DataFrame:
    """Rows (id, stratum, n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words), and key, where a column for it is named."""
    stratum = F.lit("") if stratum_col is None else F.coalesce(F.col(stratum_col).cast("string"), F.lit(""))
    names = ["id", "stratum"] if key_col is None else ["id", "stratum", "key"]
    rows = df.select(F.col(id_col).alias("id"), stratum.alias("stratum"), *([F.col(key_col).alias("key")] if key_col else []), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("t"))
    rows = rows.select(*names, words_of(F.col("t")).alias("words"), F.regexp_count("t", F.lit(SYMBOLS)).cast("bigint").alias("n_symbols"), _lines(F.col("t")).alias("lines"))
    low = F.expr("shiftleft(1L, cast(ceil(log2(size(words) + 1)) as int)) - 1")
    rows = rows.select(
        *names, "words", "n_symbols",
        F.size("words").cast("bigint").alias("n_words"),
        F.length(F.array_join("words", "")).cast("bigint").alias("word_chars"),
        F.size("lines").cast("bigint").alias("n_lines"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("bigint").alias("n_dup_lines"),
        low.alias("low"),
    )
    numbers = [*names, "n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines"]
    rows = rows.select(*numbers, "words", "low", _window_keys().alias("keys"))
    # windows that may repeat by their hash; then by their words
    rows = rows.select(*numbers, "words", "low", _same_beside("keys", lambda x: x.bitwiseAND(F.bitwise_not("low"))).alias("maybe"))
    spelt = lambda x: F.struct(F.concat_ws(" ", *[F.col("words")[(x.bitwiseAND(F.col("low")) + k).cast("int")] for k in range(3)]).alias("g"), x.bitwiseAND(F.col("low")).alias("p"))
    rows = rows.select(*numbers, F.array_sort(F.transform("maybe", spelt)).alias("spelt"))
    rows = rows.select(*numbers, F.sort_array(F.transform(_same_beside("spelt", lambda x: x["g"]), lambda x: x["p"])).alias("at"))
    covered = F.transform("at", lambda p, j: F.least(F.lit(3), F.coalesce(F.get(F.col("at"), j + 1) - p, F.lit(3))).cast("bigint"))
    return rows.select(*numbers, F.aggregate(covered, F.lit(0).cast("bigint"), lambda a, x: a + x).alias("n_repeat_words"))


def allowed(n: Column, alpha: float, level: Column) -> Column:
    """The largest k such that k or fewer of n, each with probability alpha, has probability at most level; -1 if there is none."""
    begin = F.struct((n * F.log1p(F.lit(-alpha))).alias("term"), F.lit(0.0).alias("cdf"), F.lit(-1).cast("bigint").alias("k"))

    def step(a, i):
        cdf = a["cdf"] + F.exp(a["term"])
        ratio = F.log((n - i).cast("double") / (i + 1)) + F.log(F.lit(alpha / (1 - alpha)))
        return F.struct(F.when(i < n, a["term"] + ratio).otherwise(F.lit(-1e9)).alias("term"), cdf.alias("cdf"), F.when(cdf <= level, i.cast("bigint")).otherwise(a["k"]).alias("k"))

    return F.aggregate(F.sequence(F.lit(0).cast("bigint"), F.ceil(n * alpha)), begin, step, lambda a: a["k"])


def cutoffs(counted: DataFrame, labels: DataFrame, risk: Risk = Risk(), label_id: str = "doc_id", label_col: str = "quality") -> DataFrame:
    """Rows (stratum, rule, cutoff) from feature rows and labels (1 is good, 0 is bad)."""
    known = labels.select(F.col(label_id).alias("id"), F.col(label_col).cast("int").alias("label")).where("id is not null and label in (0, 1)").groupBy("id").agg(F.min("label").alias("label"))
    measured = counted.where(f"not ({BASE_FAILED})").join(known, "id")
    each = F.array(*[F.named_struct(F.lit("rule"), F.lit(name), F.lit("value"), F.expr(what).cast("bigint")) for name, what in RULES.items()])
    spread = measured.select("stratum", "label", F.explode(each).alias("e")).select("stratum", "label", "e.rule", "e.value")
    bins = spread.groupBy("stratum", "rule", "value").agg(F.sum("label").alias("good"), F.sum(1 - F.col("label")).alias("bad"))
    # from here on there is a row for each stratum, rule and distinct whole value
    above = F.sort_array(F.collect_list(F.struct("value", "good", "bad")), asc=False)
    bins = materialize(bins, "quality-bins")
    level = risk.delta / max(1, bins.select("stratum", "rule").distinct().count())
    tests = bins.groupBy("stratum", "rule").agg(F.sum("good").alias("n"), above.alias("bins"))
    tests = tests.select("stratum", "rule", "bins", allowed(F.col("n"), risk.alpha / len(RULES), F.lit(level)).alias("k"))

    zero = F.struct(
        F.lit(0).cast("bigint").alias("good"), F.lit(0).cast("bigint").alias("bad"), F.lit(0.0).alias("gain"), F.lit(None).cast("bigint").alias("cutoff")
    )

    def step(a, b):  # a: rows above b's value; cutting at it rejects those
        gain = a["bad"] - F.lit(risk.harm) * a["good"]
        better = (a["good"] <= F.col("k")) & (gain > a["gain"])
        return F.struct((a["good"] + b["good"]).alias("good"), (a["bad"] + b["bad"]).alias("bad"), F.when(better, gain).otherwise(a["gain"]).alias("gain"), F.when(better, b["value"]).otherwise(a["cutoff"]).alias("cutoff"))

    return tests.select("stratum", "rule", F.aggregate("bins", zero, step, lambda a: a["cutoff"]).alias("cutoff")).where("cutoff is not null")


def verdicts(counted: DataFrame, cuts: DataFrame) -> DataFrame:
    """Feature rows with base_failed and kept."""
    pivot = [F.max(F.when(F.col("rule") == r, F.col("cutoff"))).alias(f"cut_{r}") for r in RULES]
    own = cuts.groupBy("stratum").agg(*pivot)
    joined = counted.join(own, "stratum", "left")
    passed = F.lit(True)
    for r, what in RULES.items():
        passed &= F.coalesce(F.expr(what) <= F.col(f"cut_{r}"), F.lit(True))
    base = F.expr(BASE_FAILED)
    return joined.select(*counted.columns, base.alias("base_failed"), (~base & passed).alias("kept"))


def judge(df: DataFrame, labels: DataFrame, risk: Risk = Risk(), id_col: str = "doc_id", text_col: str = "text", stratum_col: str | None = "lang", key_col: str | None = None) -> DataFrame:
    """Features and verdicts of all rows of df, with cutoffs learnt from those that have a label."""
    counted = materialize(features(df, id_col, text_col, stratum_col, key_col), "quality-features")
    return verdicts(counted, materialize(cutoffs(counted, labels, risk), "quality-cutoffs"))
