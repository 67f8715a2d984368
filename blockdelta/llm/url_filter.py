"""URL filter: rules by host and path, and for all other addresses a ratio of character language models. DataFrame functions only.

Addresses that a rule settles train two Markov models of the next character, one of allowed and one of blocked addresses. Counts of
one to four characters back are mixed by Witten-Bell weights, from the longest context seen down to an even
distribution; every context counts, however rare. An address's score is its log-likelihood difference per character; addresses of
one fold are kept from training, and the cut lies midway between what the given part of their allowed ones stay below
and what the same part of their blocked ones exceed.

The different longest sequences of all addresses are weighed once, by joins that grow with their number. Sequences that make up at least
one part in ``HOT_PARTS`` of all characters are by arithmetic no more than that many and meet the addresses by broadcast; the
others by shuffle, and only their characters move.

Defined cases: a null address, or one without ``://``, has empty host and path; an address without characters is scored by its end alone; if one kind has
no training rows at all the models are silent and allow; an empty table gives no rows; rows repeated under one id are judged each.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, staged

#: Characters of the longest n-gram, and the size of the even distribution.
ORDER, SYMBOLS = 4, 256
#: Sequences of at least this part of all characters go by broadcast.
HOT_PARTS = 100_000
#: Addresses with this remainder of five calibrate; the others train.
CALIBRATION_FOLD = 0


@dataclass(frozen=True)
class Rule:
    verdict: str
    host: str
    path: str

    @property
    def name(self) -> str:
        return self.host + self.path

    def fits(self, host: Column, path: Column) -> Column:
        return ((host == self.host) | F.endswith(host, F.lit("." + self.host))) & F.startswith(path, F.lit(self.path))


def address_parts(url: Column) -> tuple[Column, Column]:
    """Host, A-Z lower-cased, and path."""
    text, pattern = F.coalesce(url, F.lit("")), r"^(?s).*?://([^/?#]*)([^?#]*)"
    return ascii_lower(F.regexp_extract(text, pattern, 1)), F.regexp_extract(text, pattern, 2)


def longest_rule(rules: list[Rule], host: Column, path: Column, attribute: str) -> Column:
    """The name or verdict of the longest rule that fits; null if none does."""
    out = F.lit(None).cast("string")
    for rule in sorted(rules, key=lambda r: len(r.name)):
        out = F.when(rule.fits(host, path), F.lit(getattr(rule, attribute))).otherwise(out)
    return out


def grams(pages: DataFrame, *keep: str) -> DataFrame:
    """For every character of host and path, with an end mark, the last ORDER characters up to it; the beginning is padded."""
    padded = F.split(F.concat(F.lit("\u0002" * (ORDER - 1)), F.col("host"), F.col("path"), F.lit("\u0003")), "")
    window = F.transform(F.sequence(F.lit(1), F.length("host") + F.length("path") + 1), lambda i: F.concat(*[F.element_at("padded", i + k) for k in range(ORDER)]))
    return pages.withColumn("padded", padded).select(*keep, F.explode(window).alias("gram"))


def sequence_counts(train: DataFrame) -> DataFrame:
    """(s, a, b): how often each sequence of up to ORDER characters stands in allowed and in blocked addresses; ``train`` has allowed (boolean), host and path."""
    longest = grams(train, "allowed").groupBy("gram").agg(F.sum(F.col("allowed").cast("long")).alias("a"), F.sum((~F.col("allowed")).cast("long")).alias("b"))
    parts = longest.select("a", "b", F.explode(F.array(*[F.expr(f"right(gram, {k})") for k in range(1, ORDER + 1)])).alias("s"))
    return staged(parts.groupBy("s").agg(F.sum("a").alias("a"), F.sum("b").alias("b")), "url-counts")


def weigh(seen: DataFrame, counts: DataFrame) -> DataFrame:
    """``seen`` (gram, n) with x, the log-likelihood difference of the last character after the others."""
    followers = [f(F.col(c)) for c in "ab" for f in (F.sum, lambda x: F.sum((x > 0).cast("long")))]
    follow = counts.where("length(s) > 1").groupBy(F.expr("left(s, length(s) - 1)").alias("c")).agg(*[f.alias(n) for f, n in zip(followers, ("all_a", "kinds_a", "all_b", "kinds_b"))])
    follow = staged(follow, "url-contexts")
    first = counts.where("length(s) = 1").agg(*followers).first()
    total = dict(zip(("all_a", "kinds_a", "all_b", "kinds_b"), (F.lit(x or 0) for x in first)))
    rows, p = seen, {"a": F.lit(1.0 / SYMBOLS), "b": F.lit(1.0 / SYMBOLS)}
    for k in range(1, ORDER + 1):
        own = counts.where(F.length("s") == k).select(F.col("s").alias(f"s{k}"), F.col("a").alias(f"a{k}"), F.col("b").alias(f"b{k}"))
        rows = rows.join(own, F.expr(f"right(gram, {k})") == F.col(f"s{k}"), "left")
        if k > 1:
            context = follow.where(F.length("c") == k - 1).select(*[F.col(c).alias(f"{c}{k}") for c in follow.columns])
            rows = rows.join(context, F.expr(f"left(right(gram, {k}), {k - 1})") == F.col(f"c{k}"), "left")
            total = {c: F.coalesce(f"{c}{k}", F.lit(0)) for c in total}
        for kind in "ab":
            n, every, kinds = F.coalesce(f"{kind}{k}", F.lit(0)), total[f"all_{kind}"], total[f"kinds_{kind}"]
            p[kind] = F.when(every > 0, (n + kinds * p[kind]) / (every + kinds)).otherwise(p[kind])
    return staged(rows.select("gram", "n", (F.ln(p["a"]) - F.ln(p["b"])).alias("x")), "url-weights")


def log_ratio(pages: DataFrame, counts: DataFrame) -> DataFrame:
    """(rid, score) of ``pages`` (rid, host, path): the mean log-likelihood difference per character."""
    seen = staged(grams(pages).groupBy("gram").agg(F.count(F.lit(1)).alias("n")), "url-seen")
    weights = weigh(seen, counts)
    floor = max(1, (seen.agg(F.sum("n")).first()[0] or 0) // HOT_PARTS)
    rows = grams(pages, "rid")
    hot = F.broadcast(weights.where(F.col("n") >= floor).select(F.col("gram").alias("g"), "x"))
    frequent = rows.join(hot, F.col("gram") == F.col("g")).select("rid", "x")
    rare = rows.join(hot.select("g"), F.col("gram") == F.col("g"), "left_anti").join(weights.where(F.col("n") < floor).select("gram", "x"), "gram").select("rid", "x")
    # Sums are rounded, as the order of addition is not fixed.
    parts = [part.groupBy("rid").agg(F.sum("x").alias("x"), F.count(F.lit(1)).alias("n")) for part in (frequent, rare)]
    return parts[0].unionByName(parts[1]).groupBy("rid").agg(F.round(F.sum("x") / F.sum("n"), 9).alias("score"))


def judge(pages: DataFrame, rules: list[Rule], tail: float = 0.01, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """Per row: id, host, path, rule, verdict and score."""
    host, path = address_parts(F.col(url_col))
    named = pages.select(F.col(id_col).alias("id"), host.alias("host"), path.alias("path"))
    named = named.withColumns({"rule": longest_rule(rules, F.col("host"), F.col("path"), "name"), "settled": longest_rule(rules, F.col("host"), F.col("path"), "verdict")})
    named = staged(named.withColumn("rid", F.monotonically_increasing_id()), "url-pages")
    fold = F.pmod(F.xxhash64("host", "path"), F.lit(5))
    known = named.where(F.col("settled").isNotNull()).withColumn("allowed", F.col("settled") == "allow")
    kinds = known.where(fold != CALIBRATION_FOLD).agg(F.max("allowed"), F.min("allowed")).first()
    if kinds[0] is not True or kinds[1] is not False:
        return named.select(F.col("id").alias(id_col), "host", "path", "rule", F.coalesce("settled", F.lit("allow")).alias("verdict"), F.lit(0.0).alias("score"))
    counts = sequence_counts(known.where(fold != CALIBRATION_FOLD))
    scores = staged(log_ratio(named, counts), "url-scores")
    judged = named.join(scores, "rid")
    held = judged.where(F.col("settled").isNotNull() & (fold == CALIBRATION_FOLD))
    allowed, blocked = (F.when(F.col("settled") == kind, F.col("score")) for kind in ("allow", "block"))
    low, high = held.agg(F.percentile_approx(allowed, tail, 10_000), F.percentile_approx(blocked, 1 - tail, 10_000)).first()
    cut = (low + high) / 2 if low is not None and high is not None else 0.0
    by_model = F.when(F.col("score") < F.lit(cut), F.lit("block")).otherwise(F.lit("allow"))
    return judged.select(F.col("id").alias(id_col), "host", "path", "rule", F.coalesce("settled", by_model).alias("verdict"), "score")
