"""URL filter: rules for hosts and paths first, then the ratio of two character language models.

Two variable-order Markov models are fitted to the URLs that rules accept and reject. A character's
probability after the longest context is interpolated with the shorter ones by Witten-Bell weights:
P(c | ctx) = (n(ctx c) + t(ctx) P(c | shorter)) / (n(ctx) + t(ctx)), t: distinct characters seen after
ctx. A URL's score is the difference of log-likelihoods per character; the cutoff is calibrated on
held-out URLs with rule verdicts. All counting, smoothing and scoring is joins and grouped sums over
character windows, so the models grow with the input and live in no single memory. Scores are sums
of whole micro-nats: the same in every run.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfeat.plans.state import Workspace

BROADCAST_GRAMS = 100_000  # rows of short n-grams sent to all tasks; more are shuffled
HOT = 1000  # a window with over 1 / HOT of all rows is hot: there are fewer than HOT of them

#: (verdict, host, path) of the contract, fixed values
RULES = (("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/"))
ORDER = 4
PAD, STOP = "\x02", "\x03"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    u = F.coalesce(url, F.lit(""))
    rest = F.when(F.instr(u, "://") > 0, F.substring(u, F.instr(u, "://") + 3, F.length(u))).otherwise(F.lit(""))
    return F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), UPPER, LOWER)


def path_of(url: Column) -> Column:
    u = F.coalesce(url, F.lit(""))
    rest = F.when(F.instr(u, "://") > 0, F.substring(u, F.instr(u, "://") + 3, F.length(u))).otherwise(F.lit(""))
    return F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)


def rule_of(host: Column, path: Column, rules: tuple = RULES) -> Column:
    """Struct (rule, verdict) of the longest rule that fits, or null."""
    out = F.lit(None)
    for verdict, h, p in sorted(rules, key=lambda r: (len(r[1] + r[2]), r[1] + r[2])):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        out = F.when(fits, F.struct(F.lit(h + p).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


def windows(urls: DataFrame, order: int = ORDER) -> DataFrame:
    """(u, y, w): for each character of a URL and its end, the character after its ``order`` predecessors."""
    padded = F.concat(F.lit(PAD * order), "url", F.lit(STOP))
    return urls.select("u", "y", padded.alias("p"), F.explode(F.sequence(F.lit(1), F.length("url") + 1)).alias("i")).select("u", "y", F.substring("p", F.col("i"), F.lit(order + 1)).alias("w"))


def log_ratios(ws: Workspace, train: DataFrame, wanted: DataFrame, order: int = ORDER) -> DataFrame:
    """(w, micro): log P(accepted) - log P(rejected) of each wanted window's last character, in micro-nats.

    train: (w, good, bad), counts of each window in accepted and rejected URLs.
    """
    alphabet = 1 + (train.select(F.right("w", F.lit(1))).distinct().count())
    # P of order -1: all characters alike, one more for those never seen
    p = wanted.select("w", F.lit(1.0 / alphabet).alias("pg"), F.lit(1.0 / alphabet).alias("pb"))
    for k in range(order + 1):
        grams = train.groupBy(F.right("w", F.lit(k + 1)).alias("g")).agg(F.sum("good").alias("ng"), F.sum("bad").alias("nb"))
        grams = ws.save(grams, f"grams-{k}")
        ctx = grams.groupBy(F.substring("g", 1, k).alias("c")).agg(F.sum("ng").alias("tg"), F.sum("nb").alias("tb"), F.sum((F.col("ng") > 0).cast("long")).alias("dg"), F.sum((F.col("nb") > 0).cast("long")).alias("db"))
        few = grams.count() <= BROADCAST_GRAMS  # short ones, which many windows share
        own = p.withColumn("g", F.right("w", F.lit(k + 1))).withColumn("c", F.substring("g", 1, k))
        own = own.join(F.broadcast(grams) if few else grams, "g", "left")
        if k:
            own = own.join(F.broadcast(ctx) if few else ctx, "c", "left")
        else:  # the empty context: one row of totals, if there is any
            total = ctx.drop("c").first()
            own = own.withColumns({n: F.lit(total[n] if total else 0) for n in ("tg", "tb", "dg", "db")})

        def mixed(q: str, n: str, t: str, d: str) -> Column:
            total = F.coalesce(F.col(t), F.lit(0)) + F.coalesce(F.col(d), F.lit(0))
            return F.when(total == 0, F.col(q)).otherwise((F.coalesce(F.col(n), F.lit(0)) + F.coalesce(F.col(d), F.lit(0)) * F.col(q)) / total)

        p = ws.save(own.select("w", mixed("pg", "ng", "tg", "dg").alias("pg"), mixed("pb", "nb", "tb", "db").alias("pb")), f"order-{k}")
    return p.select("w", F.round(1e6 * (F.log("pg") - F.log("pb"))).cast("long").alias("micro"))


def calibrate(scored: DataFrame) -> int:
    """The cutoff on micro-nats per character with the least sum of both error rates, from held-out
    URLs (y true or false, s); of cutoffs that part them alike the nearest to zero. Histogram by whole
    hundredths of a nat."""
    bins = scored.groupBy(F.floor(F.col("s") / 10_000).alias("b")).agg(F.sum(F.col("y").cast("long")).alias("g"), F.sum((~F.col("y")).cast("long")).alias("x")).collect()
    good, bad = sum(r["g"] for r in bins), sum(r["x"] for r in bins)
    if not good or not bad:
        return 0
    bins.sort(key=lambda r: r["b"])
    best, below_g, below_b, low = (2.0, 0, 0), 0, 0, None
    for r in [*bins, None]:
        high = r["b"] if r else None  # any cutoff in low .. high parts the URLs in the same way
        cut = 10_000 * (min(max(0, low), high) if low is not None and high is not None else min(0, high) if high is not None else max(0, low))
        low = high + 1 if r else None
        err = below_g / good + (bad - below_b) / bad
        best = min(best, (round(err, 9), abs(cut), cut))
        if r:
            below_g, below_b = below_g + r["g"], below_b + r["x"]
    return int(best[2])


def judge(spark: SparkSession, pages: DataFrame, id_col: str = "page_id", url_col: str = "url", rules: tuple = RULES, order: int = ORDER, ws: Workspace | None = None) -> DataFrame:
    """(id, host, path, rule, verdict, score): one row per row of pages; score is null where a rule decides.

    Null urls and urls without '://' have empty host and path; the models judge the text as it stands,
    whole however long, and an empty text scores by its end alone. A null id and repeated rows are carried
    as they are; other columns play no part. Without URLs of both verdicts the models are alike and
    scores are 0, which is allowed. No pages: an empty result.
    """
    ws = ws or Workspace(spark, "urls")
    url = F.coalesce(F.col(url_col), F.lit(""))
    seen = pages.select(F.col(id_col).alias("id"), url.alias("url"), F.xxhash64(url).alias("u"), host_of(F.col(url_col)).alias("host"), path_of(F.col(url_col)).alias("path")).withColumn("by", rule_of(F.col("host"), F.col("path"), rules))
    seen = ws.save(seen.select("id", "url", "u", "host", "path", F.col("by.rule").alias("rule"), F.col("by.verdict").alias("given")), "urls")
    fold = F.conv(F.substring(F.md5("url"), 1, 8), 16, 10).cast("long") % 5 == 0
    # all rows count for the models, as often as they stand; each text is cut into windows once
    texts = seen.groupBy("url", "u").agg(F.count("*").alias("m"), F.first("given").alias("given")).select("url", "u", "m", (F.col("given") == "allow").alias("y"), fold.alias("held"))
    texts = ws.save(texts, "texts")
    cut = windows(texts.filter("y is not null and not held").select("u", F.struct("y", "m").alias("y"), "url"), order)
    train = ws.save(cut.groupBy("w").agg(F.sum(F.when(F.col("y.y"), F.col("y.m")).otherwise(0)).alias("good"), F.sum(F.when(~F.col("y.y"), F.col("y.m")).otherwise(0)).alias("bad")), "counts")
    ask = windows(texts.filter("y is null or held"), order)
    ask = ws.save(ask.groupBy("u", "w").agg(F.count("*").alias("n")), "asked")
    often = ws.save(ask.groupBy("w").agg(F.count("*").alias("m")), "asked-windows")
    ratio = ws.save(log_ratios(ws, train, often.select("w"), order).join(often, "w").select("w", "m", "micro"), "ratios")
    rows = ask.count()
    # the windows that most urls begin with would all go to one task: their ratios go to the rows instead
    hot = ratio.filter(F.col("m") * HOT > rows).select("w", "micro")
    parts = ask.join(F.broadcast(hot), "w"), ask.join(F.broadcast(hot.select("w")), "w", "left_anti").join(ratio.select("w", "micro"), "w")
    sums = [x.groupBy("u").agg(F.sum(F.col("n") * F.col("micro")).alias("sum")) for x in parts]
    total = sums[0].union(sums[1]).groupBy("u").agg(F.sum("sum").alias("sum"))
    scored = ws.save(texts.filter("y is null or held").join(total, "u").select("u", "url", "y", F.floor(F.col("sum") / (F.length("url") + 1)).alias("s")), "scores")
    cutoff = calibrate(scored.filter("y is not null"))
    verdict = F.coalesce(F.col("given"), F.when(F.col("s") >= cutoff, F.lit("allow")).otherwise(F.lit("block")))
    return seen.join(scored.filter("y is null").select("url", "s"), "url", "left").select("id", "host", "path", "rule", verdict.alias("verdict"), (F.col("s") / 1e6).alias("score"))
