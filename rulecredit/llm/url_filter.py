"""URL filter: explicit host/path rules, then a character language-model ratio.

Two smoothed variable-order Markov models over all characters are estimated from the URLs that
the rules accept and reject: a table of every context of up to ``ORDER`` characters that such
URLs hold, with what follows it, so it grows with the URLs. A next character's probability
interpolates all orders of its context that were seen, down to uniform (Witten-Bell). A
URL no rule decides is scored by its length-normalised log-likelihood difference and blocked
below a cut that is calibrated on a fifth of the rule-decided URLs (by hash), which the
models do not learn from: the cut with the best balanced accuracy there.

All of it is joins and aggregates without user functions: URLs become rows of ``ORDER`` + 1
characters, distinct ones look their counts up once, and the summed ratios (whole
millionths, so sums do not depend on row order) return to the URLs. Common pieces ("https:")
and common URLs are hot keys, whose joins are spread.

Defined results: null URLs and URLs without ``://`` have empty host and path and no
rule; a null URL scores 0 as the empty string does (``allow`` unless the calibrated cut is
above zero); repeated URLs are judged alike, and each row is kept; the longest fitting rule wins,
and rules of one length cannot both fit; a very long URL is as many rows as it has characters;
with no labelled URL, or none of one side, every score is 0 and every verdict ``allow``; an empty
table gives an empty result; columns named like an output column are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rulecredit.llm.runtime import SharedStore, spread_join

#: Fixed values: (verdict, host, path) rules.
RULES = (
    ("allow", "org", "/"),
    ("block", "example.org", "/es/"),
    ("block", "example.org", "/en/1"),
    ("allow", "com", "/fr/"),
    ("block", "com", "/de/"),
)
#: Longest context; fixed marks before and after a URL; probability of a character before any was seen.
ORDER = 5
START, END = "\x02", "\x03"
UNIFORM = 1.0 / 256
#: One labelled URL in so many calibrates the cut. Scores are compared in so many steps a unit.
FOLDS, STEPS = 5, 1000
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def split_url(url: Column) -> tuple[Column, Column]:
    """Host and path of a URL as the rules see them."""
    u = F.coalesce(url, F.lit(""))
    at = F.instr(u, "://")
    rest = F.when(at > 0, F.substr(u, at + 3)).otherwise("")
    host = F.translate(F.regexp_extract(rest, r"(?s)^[^/?#]*", 0), UPPER, LOWER)
    path = F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)
    return host, path


def rule_column(host: Column, path: Column) -> Column:
    """Struct (rule, verdict) of the longest fitting rule, null where none fits."""
    out = None
    for verdict, h, p in sorted(RULES, key=lambda r: (-len(r[1] + r[2]), r[1] + r[2])):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        hit = F.struct(F.lit(h + p).alias("rule"), F.lit(verdict).alias("verdict"))
        out = F.when(fits, hit) if out is None else out.when(fits, hit)
    return out


def pieces(url: Column) -> Column:
    """The URL's characters, each with the ORDER characters before it."""
    padded = F.concat(F.lit(START * ORDER), F.translate(url, UPPER, LOWER), F.lit(END))
    return F.transform(F.sequence(F.lit(1), F.length(padded) - ORDER), lambda i: F.substring(padded, i, F.lit(ORDER + 1)))


def learn(labelled: DataFrame) -> DataFrame:
    """The model table of (url, accepted): rows (kind, key, acc, rej, acc_kinds, rej_kinds).

    Kind ``p``: a context and a character, with how often both sides hold it. Kind ``c``: a context,
    with how often it occurs and how many different characters follow it.
    """
    held = labelled.select("accepted", F.explode(pieces(F.col("url"))).alias("piece"))
    whole = held.groupBy("piece").agg(F.count_if("accepted").alias("acc"), F.count_if(~F.col("accepted")).alias("rej"))
    keys = F.explode(F.array(*[F.expr(f"right(piece, {k + 1})") for k in range(ORDER + 1)]))
    pairs = whole.select(keys.alias("key"), "acc", "rej").groupBy("key").agg(F.sum("acc").alias("acc"), F.sum("rej").alias("rej"))
    contexts = pairs.groupBy(F.expr("left(key, length(key) - 1)").alias("key")).agg(
        F.sum("acc").alias("acc"),
        F.sum("rej").alias("rej"),
        F.count_if(F.col("acc") > 0).alias("acc_kinds"),
        F.count_if(F.col("rej") > 0).alias("rej_kinds"),
    )
    none = F.lit(0).cast("long")
    as_pairs = pairs.select(F.lit("p").alias("kind"), "key", "acc", "rej", none.alias("acc_kinds"), none.alias("rej_kinds"))
    return as_pairs.unionByName(contexts.select(F.lit("c").alias("kind"), "key", "acc", "rej", "acc_kinds", "rej_kinds"))


def ratios(wanted: DataFrame, model: DataFrame) -> DataFrame:
    """(piece, rows, ratio) of (piece, rows): log(P_accepted / P_rejected) of its last character, in millionths."""
    cell = lambda kind, k, key: F.struct(F.lit(kind).alias("kind"), F.lit(k).alias("k"), F.expr(key).alias("key"))
    lookups = [cell("p", k, f"right(piece, {k + 1})") for k in range(ORDER + 1)]
    lookups += [cell("c", k, f"left(right(piece, {k + 1}), {k})") for k in range(ORDER + 1)]
    rows = wanted.select("piece", "rows", F.explode(F.array(*lookups)).alias("l")).select("piece", "rows", "l.*")
    found = rows.join(model, ["kind", "key"])
    pick = lambda kind, k, c: F.coalesce(F.sum(F.when((F.col("kind") == kind) & (F.col("k") == k), F.col(c))), F.lit(0))
    sums = found.groupBy("piece").agg(
        *[pick("p", k, side).alias(f"p{k}_{side}") for k in range(ORDER + 1) for side in ("acc", "rej")],
        *[pick("c", k, c).alias(f"c{k}_{c}") for k in range(ORDER + 1) for c in ("acc", "rej", "acc_kinds", "rej_kinds")],
    )
    logs = {}
    for side in ("acc", "rej"):
        prob = F.lit(UNIFORM)
        for k in range(ORDER + 1):
            n, t, d = F.col(f"p{k}_{side}"), F.col(f"c{k}_{side}"), F.col(f"c{k}_{side}_kinds")
            prob = F.when(t + d > 0, (n + d * prob) / (t + d)).otherwise(prob)
        logs[side] = F.log(prob)
    ratio = F.round(1e6 * (logs["acc"] - logs["rej"])).cast("long")
    return wanted.join(sums.select("piece", ratio.alias("ratio")), "piece", "left").na.fill(0, ["ratio"])


def score_urls(urls: DataFrame, model: DataFrame, store: SharedStore) -> DataFrame:
    """(url, score) of distinct URLs: the mean ratio of their characters and the end mark."""
    rows = urls.select("url", F.explode(pieces(F.col("url"))).alias("piece"))
    known = store.write(ratios(rows.groupBy("piece").agg(F.count("*").alias("rows")), model), "ratios")
    scored = spread_join(rows, known.select("piece", "rows", "ratio"), ["piece"], "rows", ["url"])
    return scored.groupBy("url").agg((F.sum("ratio") / (1e6 * F.count("*"))).alias("score"))


def calibrate(scored: DataFrame) -> float:
    """The cut on (score, accepted) with the best mean of the two sides' shares of right verdicts.

    Works on a histogram of scores in steps; of equally good cuts the middle one is taken. 0 when a side is empty.
    """
    steps = scored.groupBy(F.floor(F.col("score") * STEPS).alias("step")).agg(
        F.count_if("accepted").alias("acc"), F.count_if(~F.col("accepted")).alias("rej")
    )
    order = Window.orderBy("step")
    below, all_ = order.rowsBetween(Window.unboundedPreceding, Window.currentRow), Window.partitionBy()
    # URLs up to a step are blocked when the cut lies above it; as many rows as scores have steps
    part = lambda side: F.try_divide(F.sum(side).over(below), F.sum(side).over(all_))
    share = part("rej") - part("acc")
    middle = (F.col("step") + 1 + F.lead("step", 1).over(order)) / 2
    both = steps.withColumns({"good": F.round(share, 9), "cut": F.coalesce(middle, F.col("step") + 1)}).where("good > 0")
    best = both.where(F.col("good") == both.agg(F.max("good")).scalar())
    row = best.agg(F.percentile("cut", F.lit(0.5)).alias("m")).first()
    return 0.0 if row["m"] is None else row["m"] / STEPS


def judge_urls(pages: DataFrame, url: str = "url", model: DataFrame | None = None) -> DataFrame:
    """``pages`` with host, path, rule, score and verdict.

    ``model``: a table that :func:`learn` made; by default one of the rule-decided rows of ``pages``.
    """
    store = SharedStore(pages.sparkSession, "urls")
    cols = [c for c in pages.columns if c not in {"host", "path", "rule", "score", "verdict"}]
    host, path = split_url(F.col(url))
    base = pages.select(*cols).withColumns({"host": host, "path": path})
    base = base.withColumn("_r", rule_column(F.col("host"), F.col("path"))).withColumn("_url", F.coalesce(url, F.lit("")))
    fold = F.pmod(F.xxhash64("_url"), F.lit(FOLDS))
    ruled = base.where("_r is not null").select(F.col("_url").alias("url"), (F.col("_r.verdict") == "allow").alias("accepted"), fold.alias("fold"))
    if model is None:
        model = store.write(learn(ruled.where("fold > 0").select("url", "accepted")), "model")
    wanted = base.where(F.col("_r").isNull() | (fold == 0)).groupBy(F.col("_url").alias("url")).agg(F.count("*").alias("rows"))
    wanted = store.write(wanted, "wanted")
    scores = store.write(score_urls(wanted.select("url"), model, store).join(wanted, "url"), "scores")
    both_sides = model.agg((F.sum("acc") > 0).alias("a"), (F.sum("rej") > 0).alias("r")).first()
    cut = calibrate(ruled.where("fold = 0").join(scores, "url").select("score", "accepted")) if both_sides["a"] and both_sides["r"] else None
    store.keep("scores")
    if cut is None:  # nothing to tell the sides apart by
        return base.select(
            *cols, "host", "path", F.col("_r.rule").alias("rule"), F.lit(0.0).alias("score"), F.coalesce(F.col("_r.verdict"), F.lit("allow")).alias("verdict")
        )
    known = scores.select(F.col("url").alias("_url"), F.col("rows").alias("_rows"), F.col("score").alias("_score"))
    open_ = spread_join(base.where("_r is null"), known, ["_url"], "_rows", cols[:1])
    verdict = F.when(F.col("_score") < cut, "block").otherwise("allow")
    out = [*cols, "host", "path"]
    judged = open_.select(*out, F.lit(None).cast("string").alias("rule"), F.col("_score").alias("score"), verdict.alias("verdict"))
    ruled_rows = base.where("_r is not null").select(*out, F.col("_r.rule").alias("rule"), F.lit(None).cast("double").alias("score"), F.col("_r.verdict").alias("verdict"))
    return judged.unionByName(ruled_rows)


def op6_url_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    return judge_urls(pages).select("page_id", "host", "path", "rule", "verdict", "score")
