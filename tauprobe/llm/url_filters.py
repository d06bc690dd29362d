"""URL filters: host and path rules, then association rules mined with FP-growth, in DataFrame functions only.

`apply_rules` gives each URL the longest rule that fits. Where none does, the verdict is that of the mined rules: URL
tokens (host labels, path segments, query keys) of labelled pages are the items, with the label as one more; Spark's
FP-growth finds combinations that imply the block label, and those with too little support, confidence or lift are pruned.
Only minimal rules count, since what fits a longer rule fits the shorter one within it. So a token that is a rule by itself
takes no part in the mining, and tokens that occur in the same pages are mined as one (a class, any of whose tokens will do).
A page brings at most `Mining.width` classes to FP-growth, those most often blocked, so a page of many tokens cannot make it
list all their combinations. That is complete unless a labelled page has more classes. If one has, rules are counted again
over all classes of all labelled pages, and what FP-growth cannot have seen is searched for exactly, size by size
(`_rest`), in the pages that no rule blocks so far: so a page is blocked if, and only if, it holds any combination that
implies the label. Mined rules match through an inverted index from the tokens of a rule's rarest class.

Defined results: a null URL, or one without `://`, has an empty host and path, no tokens and the default verdict; empty and
very long URLs are whole; repeated rows give repeated results; a page with several labels is bad if one of them is; without
labels, or with too few for the support, nothing is mined; an empty table gives an empty table; only the named columns are
read.
"""

from __future__ import annotations

import math
import string
from dataclasses import dataclass
from functools import reduce

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tauprobe.llm.arrow_kernels import small
from tauprobe.session import materialize

BLOCKED = "label=block"
#: Host and path rules up to this number are conditions in the plan; more of them are joined.
MOST_CONDITIONS = 500
RULES = "rule_id bigint, classes array<array<string>>"
#: Combinations of a size, besides the best of each open set, that grow in the first, quick search; a later one goes through all that are left.
PROMISING = 256
#: Where a combination (s) occurs: kind and power of two of a number of pages, number of a word of bits.
PLACE = ["kind", "weight", "block"]


@dataclass(frozen=True)
class Mining:
    #: Least share, and least number, of labelled URLs that have a combination.
    support: float = 0.002
    rows: int = 20
    confidence: float = 0.8
    lift: float = 2.0
    #: Most classes of tokens that a page brings to FP-growth; what lies beyond them is searched for by itself.
    width: int = 12


def _part(url: Column, group: int) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)([^?#]*)", group)


def host_of(url: Column) -> Column:
    return F.translate(_part(url, 1), string.ascii_uppercase, string.ascii_lowercase)


def path_of(url: Column) -> Column:
    return _part(url, 2)


def tokens_of(url: Column) -> Column:
    """Distinct tokens: h: host labels, p: path segments, q: query keys."""
    query = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^?#]*\?([^#]*)", 1)
    some = lambda kind, parts: F.transform(F.filter(parts, lambda x: x != ""), lambda x: F.concat(F.lit(kind), x))
    keys = F.transform(F.split(query, "&"), lambda x: F.substring_index(x, "=", 1))
    return F.array_distinct(F.concat(some("h:", F.split(host_of(url), r"\.")), some("p:", F.split(path_of(url), "/")), some("q:", keys)))


def apply_rules(pages: DataFrame, rules: list[tuple[str, str]], most: int = MOST_CONDITIONS) -> DataFrame:
    """pages (with columns host and path) with rule and said: the longest of the rules (text, verdict) that fits; null where none does."""
    if len(rules) > most:
        return _joined_rules(pages, rules)
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for text, said in sorted(rules, key=lambda r: (len(r[0]), r[0])):
        name, slash, rest = text.partition("/")
        fits = ((F.col("host") == name) | F.col("host").endswith("." + name)) & F.col("path").startswith(slash + rest)
        rule, verdict = F.when(fits, F.lit(text)).otherwise(rule), F.when(fits, F.lit(said)).otherwise(verdict)
    return pages.select("*", rule.alias("rule"), verdict.alias("said"))


def _joined_rules(pages: DataFrame, rules: list[tuple[str, str]]) -> DataFrame:
    """The same for any number of rules: the suffixes of the distinct hosts and paths meet the rules' hosts."""
    split = [(text, said, *(text.partition("/")[0], "".join(text.partition("/")[1:]))) for text, said in rules]
    table = small(pages.sparkSession.createDataFrame(split, "rule string, said string, suffix string, start string"))
    labels = F.split("host", r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    places = pages.select("host", "path").distinct()
    met = places.select("host", "path", F.explode(suffixes).alias("suffix")).join(table, "suffix").where(F.col("path").startswith(F.col("start")))
    best = met.groupBy("host", "path").agg(F.max(F.struct(F.length("rule").alias("n"), "rule", "said")).alias("best"))
    return pages.join(best.select("host", "path", "best.rule", "best.said"), ["host", "path"], "left").select(*pages.columns, "rule", "said")


def _tokens_of_labelled(pages: DataFrame, labels: DataFrame, id_col: str, url_col: str, label_id: str, bad: str) -> DataFrame:
    """Rows (row, tokens, bad) of the labelled pages, written once."""
    marked = labels.where(F.col(label_id).isNotNull()).groupBy(F.col(label_id).alias("id")).agg(F.max(F.coalesce(F.expr(bad), F.lit(False))).alias("bad"))
    known = pages.select(F.col(id_col).alias("id"), tokens_of(F.col(url_col)).alias("tokens")).join(marked, "id")
    return materialize(known.where("size(tokens) > 0 or bad").select(F.monotonically_increasing_id().alias("row"), "tokens", "bad"), "labelled-tokens")


def mine(pages: DataFrame, labels: DataFrame, mining: Mining = Mining(), id_col: str = "page_id", url_col: str = "url", label_id: str = "doc_id", bad: str = "toxic = 1 or quality = 0", asked: DataFrame | None = None) -> DataFrame:
    """Rows (rule_id, classes): combinations that imply the block label; a URL fits a rule with a token of each class.

    A URL of `asked` (the pages, if not given) fits one of them if it holds any such combination.
    """
    known = _tokens_of_labelled(pages, labels, id_col, url_col, label_id, bad)
    total, bad_total = known.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.col("bad").cast("bigint")), F.lit(0))).first()
    least = max(math.ceil(mining.support * total), mining.rows)
    if bad_total < least:
        return known.sparkSession.createDataFrame([], RULES)
    good_enough = (F.col("n_bad") >= least) & (F.col("n_bad") >= mining.confidence * F.col("n")) & (F.col("n_bad") * total >= mining.lift * F.col("n") * bad_total)
    counts = [F.count(F.lit(1)).alias("n"), F.sum(F.col("bad").cast("bigint")).alias("n_bad")]

    each = known.select("row", "bad", F.explode("tokens").alias("token"))
    same = [F.bit_xor(F.xxhash64("row")).alias("rows_x"), F.sum(F.pmod(F.xxhash64("row", F.lit(7)), F.lit(1 << 32))).alias("rows_s")]
    tokens = materialize(each.groupBy("token").agg(*counts, *same).where(f"n_bad >= {least}").withColumn("alone", good_enough), "frequent-tokens")  # at most tokens a page / support
    alone = tokens.where("alone").select(F.xxhash64("token").alias("rule_id"), F.array(F.array("token")).alias("classes"))
    classes = tokens.where("not alone").groupBy("n", "n_bad", "rows_x", "rows_s").agg(F.min("token").alias("class"), F.sort_array(F.collect_list("token")).alias("members"))
    classes = materialize(classes.select("class", "members", "n", F.struct((-F.col("n_bad") / F.col("n")).alias("share"), "class").alias("place")), "token-classes")
    firsts = each.join(small(classes.select(F.col("class").alias("token"), "place")), "token")
    full = materialize(firsts.groupBy("row").agg(F.first("bad").alias("bad"), F.sort_array(F.collect_list("place")).alias("places")).select("row", "bad", F.transform("places", lambda p: p["class"]).alias("classes")), "class-rows")
    n_rows, widest = full.agg(F.count(F.lit(1)), F.max(F.size("classes"))).first()
    if not n_rows:
        return alone
    items = F.slice("classes", 1, mining.width)
    rows = full.select(F.when(F.col("bad"), F.concat(items, F.array(F.lit(BLOCKED)))).otherwise(items).alias("items"))
    model = FPGrowth(itemsCol="items", minSupport=min(1.0, (least - 0.5) / n_rows), minConfidence=mining.confidence).fit(rows)
    found = model.associationRules.where(F.col("consequent") == F.array(F.lit(BLOCKED))).where(F.size("antecedent") > 1)
    n_bad = F.round(F.col("support") * n_rows).cast("bigint")
    found = found.select(F.xxhash64(F.sort_array("antecedent")).alias("rule_id"), F.col("antecedent").alias("classes"), n_bad.alias("n_bad"), F.round(n_bad / F.col("confidence")).cast("bigint").alias("n"))
    if widest <= mining.width:  # these counts are those of all classes
        return alone.union(_named(_minimal(found.where(good_enough).select("rule_id", "classes")), classes))
    found = materialize(found.select("rule_id", "classes"), "mined")
    # counted again over all classes of the pages, from each rule's rarest class
    rarest = _rarest(found, classes)
    met = full.select("row", "bad", "classes", F.explode("classes").alias("class")).join(small(rarest.select("rule_id", "class", F.col("classes").alias("wanted"))), "class")
    exact = met.where(F.size(F.array_except("wanted", "classes")) == 0).groupBy("rule_id").agg(*counts).where(good_enough).select("rule_id")
    mined = materialize(alone.union(_named(_minimal(found.join(exact, "rule_id", "left_semi")), classes)), "mined-rules")
    return mined.union(_named(_rest(full, classes, _open(pages if asked is None else asked, url_col, mined, classes), good_enough, least, mining.width), classes))


def _named(rules: DataFrame, classes: DataFrame) -> DataFrame:
    """Rules (rule_id, classes) with the tokens of each of their classes."""
    named = rules.select("rule_id", F.explode("classes").alias("class")).join(classes.select("class", "members"), "class")
    return named.groupBy("rule_id").agg(F.collect_list("members").alias("classes"))


def _open(pages: DataFrame, url_col: str, rules: DataFrame, classes: DataFrame) -> DataFrame:
    """The distinct sets of two classes or more (column classes) of the URLs that fit no rule."""
    urls = pages.select(F.col(url_col).alias("url")).where("url is not null").distinct()
    left = urls.join(matches(urls, rules), F.col("url") == F.col("matched_url"), "left_anti")
    members = small(classes.select("class", F.explode("members").alias("token")))
    held = left.select("url", F.explode(tokens_of(F.col("url"))).alias("token")).join(members, "token")
    return held.groupBy("url").agg(F.sort_array(F.collect_set("class")).alias("classes")).where("size(classes) > 1").select("classes").distinct()


def _rest(full: DataFrame, classes: DataFrame, asked: DataFrame, good_enough: Column, least: int, width: int) -> DataFrame:
    """Rules (rule_id, classes) for the sets `asked`: each fits one of them, if any combination of classes that implies the label and lies in a labelled page of more than `width` classes.

    Combinations grow by a class at a time. First only the most promising ones do (`_promising`), which settles most sets fast
    and none wrongly; then all of them for the sets that are still open. One is given up if too few bad pages have it, if no such wide page or no set that
    is still open has it, if it holds a rule, or if some class of it keeps no good page out: then it is no smallest rule, and
    no larger combination is either. Where a combination occurs is kept as words of 64 bits, a bit for each distinct set of
    classes; a number of pages is a sum of powers of two, each with words of its own. Of the rules of a size, only those are kept that open sets need.
    """
    numbers = materialize(classes.select("class", F.monotonically_increasing_id().alias("k")), "class-numbers")
    labelled = full.groupBy(F.sort_array("classes").alias("classes")).agg(F.sum(F.col("bad").cast("bigint")).alias("n_bad"), F.sum((~F.col("bad")).cast("bigint")).alias("n_good"))
    sets = labelled.withColumn("open", F.lit(False)).unionByName(asked.select("classes", F.lit(0).cast("bigint").alias("n_bad"), F.lit(0).cast("bigint").alias("n_good"), F.lit(True).alias("open")))
    sets = sets.groupBy("classes").agg(F.sum("n_bad").alias("n_bad"), F.sum("n_good").alias("n_good"), F.max("open").alias("open"))
    sets = materialize(sets.withColumn("id", F.monotonically_increasing_id()), "class-sets")
    powers = lambda kind, n: f"transform(filter(sequence(0, 40), j -> (shiftright({n}, j) & 1) = 1), j -> struct('{kind}' as kind, shiftleft(1L, j) as weight))"
    once = lambda kind, when: f"if({when}, array(struct('{kind}' as kind, 0L as weight)), array())"
    kinds = f"concat({powers('bad', 'n_bad')}, {powers('good', 'n_good')}, {once('open', 'open')}, {once('wide', f'n_bad + n_good > 0 and size(classes) > {width}')})"
    bits = sets.select(F.expr(f"inline({kinds})"), F.expr("shiftright(id, 6)").alias("block"), F.expr("shiftleft(1L, cast(id % 64 as int))").alias("bit"), "classes")
    bits = bits.select("kind", "weight", "block", "bit", F.explode("classes").alias("class")).join(small(numbers), "class")
    held = materialize(bits.groupBy(F.array("k").alias("s"), *PLACE).agg(F.bit_or("bit").alias("mask")), "combinations")
    rules, held = _promising(held, good_enough, least)
    before, size = None, 1
    while True:
        tried = _tried(held, least)
        if before is not None:
            tried = tried.join(before, "s").where("n_good < fewest").drop("fewest")
        tried = materialize(tried.withColumn("rule", good_enough), "tried")
        new, done = _needed(held, tried.where("rule"))
        rules.append(new)
        held = materialize(_cleared(held.join(tried.where("not rule").select("s"), "s", "left_semi"), done), "live")
        # larger combinations of open sets, all of whose parts are live
        ends = held.where("kind = 'open'").select(F.slice("s", 1, size - 1).alias("start"), F.col("s")[size - 1].alias("last"), "block", "mask")
        pairs = ends.join(ends.select("start", "block", F.col("last").alias("next"), F.col("mask").alias("other")), ["start", "block"]).where("last < next and (mask & other) != 0")
        larger = pairs.select(F.concat("start", F.array("last", "next")).alias("s")).distinct()
        parts = larger.select("s", F.explode(F.transform(F.sequence(F.lit(1), F.lit(size + 1)), lambda i: F.concat(F.slice("s", 1, i - 1), F.slice("s", i + 1, size + 1)))).alias("part"))
        whole = parts.join(tried.where("not rule").select(F.col("s").alias("part"), "n_good"), "part").groupBy("s").agg(F.count(F.lit(1)).alias("live"), F.min("n_good").alias("fewest"))
        before = materialize(whole.where(f"live = {size + 1}").select("s", "fewest"), "larger")
        if not before.limit(1).count():
            break
        first = before.select("s", F.slice("s", 1, size).alias("one"), F.concat(F.slice("s", 1, size - 1), F.slice("s", size + 1, 1)).alias("two"))
        first = first.join(held.withColumnRenamed("s", "one"), "one")
        both = first.join(held.select(F.col("s").alias("two"), *PLACE, F.col("mask").alias("other")), ["two", *PLACE])
        held = materialize(both.select("s", *PLACE, F.expr("mask & other").alias("mask")).where("mask != 0"), "combinations")
        size += 1
    found = reduce(DataFrame.union, rules).distinct()
    named = found.select(F.xxhash64("s").alias("rule_id"), F.explode("s").alias("k")).join(numbers, "k")
    return named.groupBy("rule_id").agg(F.collect_list("class").alias("classes"))


def _tried(held: DataFrame, least: int) -> DataFrame:
    """Rows (s, n_bad, n_good, n): the combinations that open sets, wide pages and enough bad pages have, counted over all pages."""
    many = lambda kind: F.sum(F.when(F.col("kind") == kind, F.bit_count("mask") * F.col("weight")).otherwise(0))
    some = lambda kind: F.max(F.col("kind") == kind)
    tried = held.groupBy("s").agg(many("bad").alias("n_bad"), many("good").alias("n_good"), some("open").alias("open"), some("wide").alias("wide"))
    return tried.where(f"open and wide and n_bad >= {least}").select("s", "n_bad", "n_good", (F.col("n_bad") + F.col("n_good")).alias("n"))


def _needed(held: DataFrame, rules: DataFrame) -> tuple[DataFrame, DataFrame]:
    """For each open set that fits some of the rules the one that most of them fit (column s), and these sets (block, done)."""
    fits = held.where("kind = 'open'").join(rules.select("s"), "s", "left_semi").select("s", "block", "mask")
    wanted = fits.groupBy("s").agg(F.sum(F.bit_count("mask")).alias("fitting"))
    best = fits.join(wanted, "s").select("s", "fitting", "block", _bits()).groupBy("block", "bit").agg(F.max_by("s", F.struct("fitting", "s")).alias("s"))
    best = materialize(best, "settled")
    return best.select("s").distinct(), best.groupBy("block").agg(F.bit_or(F.expr("shiftleft(1L, bit)")).alias("done"))


def _bits() -> Column:
    """The places of the bits of a mask, a row each."""
    return F.explode(F.expr("filter(sequence(0, 63), i -> (shiftright(mask, i) & 1) = 1)")).alias("bit")


def _cleared(held: DataFrame, done: DataFrame) -> DataFrame:
    """The combinations without the open sets that are done."""
    left = held.join(small(done), "block", "left")
    mask = F.when(F.col("kind") == "open", F.expr("mask & ~coalesce(done, 0L)")).otherwise(F.col("mask"))
    return left.select("s", *PLACE, mask.alias("mask")).where("mask != 0")


def _promising(held: DataFrame, good_enough: Column, least: int) -> tuple[list[DataFrame], DataFrame]:
    """Rules (s) found by growing only the combinations of the highest shares of bad pages, of all and of each open set, and single classes (held) with what is still open.

    Begins anew for the sets still open until it settles none.
    """
    rules: list[DataFrame] = []
    while True:
        settled, grown = False, held
        while True:
            tried = materialize(_tried(grown, least).withColumn("rule", good_enough), "promising")
            new, done = _needed(grown, tried.where("rule"))
            if new.limit(1).count():
                settled = True
                rules.append(new)
                held = materialize(_cleared(held, done), "combinations")
                if not held.where("kind = 'open'").limit(1).count():
                    return rules, held
                grown = _cleared(grown, done)
            ranked = tried.where("not rule").select("s", F.struct(F.col("n_bad") / F.col("n"), "n_bad", "s").alias("rank"))
            of_each = grown.where("kind = 'open'").select("s", "block", _bits()).join(ranked, "s").groupBy("block", "bit").agg(F.max_by("s", "rank").alias("s")).select("s")
            best = of_each.union(ranked.orderBy(F.desc("rank")).limit(PROMISING).select("s"))
            ends = grown.join(best, "s", "left_semi")
            both = ends.join(held.select(F.col("s")[0].alias("k"), *PLACE, F.col("mask").alias("other")), PLACE).where("not array_contains(s, k) and (mask & other) != 0")
            larger = both.groupBy(F.expr("array_sort(array_append(s, k))").alias("s"), *PLACE).agg(F.bit_or(F.expr("mask & other")).alias("mask"))
            grown = materialize(larger, "grown")
            if not grown.limit(1).count():
                break
        if not settled:
            return rules, held


def _minimal(rules: DataFrame) -> DataFrame:
    """The rules (rule_id, classes) that hold no other one."""
    rules = materialize(rules, "rules")
    index = rules.select(F.col("rule_id").alias("inner"), F.size("classes").alias("wanted"), F.explode("classes").alias("class"))
    held = rules.select("rule_id", F.size("classes").alias("size"), F.explode("classes").alias("class")).join(index, "class").where("wanted < size")
    longer = held.groupBy("rule_id", "inner", "wanted").agg(F.count(F.lit(1)).alias("had")).where("had = wanted").select("rule_id").distinct()
    return rules.join(longer, "rule_id", "left_anti")


def _rarest(rules: DataFrame, classes: DataFrame) -> DataFrame:
    """Rules (rule_id, classes) with their class that fewest pages have."""
    each = rules.select("rule_id", "classes", F.explode("classes").alias("class")).join(classes.select("class", "n"), "class")
    return each.groupBy("rule_id").agg(F.first("classes").alias("classes"), F.min_by("class", F.struct("n", "class")).alias("class"))


def matches(urls: DataFrame, rules: DataFrame, url_col: str = "url") -> DataFrame:
    """The distinct URLs (column matched_url) that fit a mined rule, through the index from the tokens of a rule's smallest class."""
    first = F.array_sort("classes", lambda a, b: F.when(F.size(a) < F.size(b), -1).when(F.size(a) > F.size(b), 1).when(a[0] < b[0], -1).when(a[0] > b[0], 1).otherwise(0))
    index = rules.select(first.alias("classes")).select("classes", F.explode(F.col("classes")[0]).alias("token"))
    held = urls.select(F.col(url_col).alias("matched_url")).distinct().select("matched_url", tokens_of(F.col("matched_url")).alias("tokens"))
    met = held.select("matched_url", "tokens", F.explode("tokens").alias("token")).join(small(materialize(index, "rule-index")), "token")
    return met.where(F.forall("classes", lambda c: F.arrays_overlap(c, F.col("tokens")))).select("matched_url").distinct()


def judge(pages: DataFrame, labels: DataFrame, rules: list[tuple[str, str]], mining: Mining = Mining(), id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """Rows (id, host, path, rule, verdict): one for each page."""
    picked = pages.select(F.col(id_col).alias("id"), F.col(url_col).cast("string").alias("url"))
    ruled = apply_rules(picked.select("id", "url", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path")), rules)
    asked = ruled.where("said is null")
    mined = mine(picked, labels, mining, "id", "url", asked=asked)
    hit = matches(asked, mined)
    joined = ruled.join(hit, ruled.url == hit.matched_url, "left")
    return joined.select("id", "host", "path", "rule", F.coalesce("said", F.when(F.col("matched_url").isNotNull(), "block"), F.lit("allow")).alias("verdict"))
