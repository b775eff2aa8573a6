"""URL filter: a rule list first, then the likelihood ratio of two character models.

The models are variable-order Markov models over the characters of host and path as they stand, one of the URLs that the rules allow
and one of those they block, with contexts of ORDER characters down to none: each context's estimate is smoothed by that of the
context one character shorter, so a context counts for as much as it was seen, and one that a class lacks falls back to the longest
that it has. URLs without a rule are judged by the length-normalised difference of log-likelihoods against a threshold half way
between the two classes' means. DataFrame functions only.

What is counted grows with the URLs: a row for every different string of ORDER + 1 characters in any URL, and for every ending of
one. These tables are written and joined, not broadcast; only strings that make up a HEAVY-th of all positions or more, at most
HEAVY of them, are sent to all tasks, so that no join key holds more than that share of the rows. Log ratios are whole millionths:
sums do not depend on the order of rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spanweave.llm.shared import stash

#: (verdict, host, path prefix). Fixed values.
RULES = (
    ("allow", "org", "/"),
    ("block", "example.org", "/es/"),
    ("block", "example.org", "/en/1"),
    ("allow", "com", "/fr/"),
    ("block", "com", "/de/"),
)
#: Code points that stand before and after a URL: control characters, which URLs do not hold unescaped.
START, END = 2, 3
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Characters of the longest context.
ORDER = 5
#: Weight of the shorter context, in observations.
SMOOTHING = 4
#: Strings that stand at this fraction of all positions or more are joined by broadcast: there are at most so many of them.
HEAVY = 1024


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, r"://([^/?#]*)", 1), F.lit("")), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"://[^/?#]*([^?#]*)", 1), F.lit(""))


def by_rules(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """(rule, verdict): of the rules that fit, the longest; null where none does."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for says, of, prefix in sorted(rules, key=lambda r: (len(r[1] + r[2]), r)):
        fits = ((host == of) | host.endswith("." + of)) & path.startswith(prefix)
        rule, verdict = F.when(fits, of + prefix).otherwise(rule), F.when(fits, says).otherwise(verdict)
    return rule, verdict


def framed(host: Column, path: Column, order: int = ORDER) -> Column:
    """What the models read: host and path, `order` starts before and an end after them."""
    return F.concat(F.lit(chr(START) * order), host, path, F.lit(chr(END)))


def positions(lines: DataFrame, order: int = ORDER) -> DataFrame:
    """The columns of `lines` without `line`, and `gram`: every character of `line` behind the `order` before it.

    Lines are taken apart once, so that a very long one costs time in proportion to its length."""
    apart = lines.withColumn("signs", F.split("line", "")).drop("line")
    each = apart.select("*", F.explode(F.sequence(F.lit(1), F.size("signs") - order)).alias("at"))
    return each.withColumn("gram", F.array_join(F.slice("signs", F.col("at"), order + 1), "")).drop("signs", "at")


def log_ratios(lines: DataFrame, order: int = ORDER, smoothing: int = SMOOTHING) -> DataFrame:
    """(gram, seen, weight): for every string of `order` + 1 characters in `lines`, at how many positions of different lines it
    stands, and millionths of ln(P allow / P block) of its last character behind the others.

    `lines` has `line` (see `framed`) and how often each class has it, `allow` and `block`; lines of neither class are read for
    the strings that have to be judged. A context's strings meet in one task: they are at most as many as there are characters."""
    sides = ("allow", "block")
    sums = [F.sum(s).alias(s) for s in sides]
    grams = stash(positions(lines, order).groupBy("gram").agg(*sums, F.count(F.lit(1)).alias("seen")))
    k = F.lit(float(smoothing))

    # No context: all characters of the class; before that, every character is as likely as the next.
    ending = grams.groupBy(F.substring("gram", order + 1, 1).alias("gram")).agg(*sums)
    whole = ending.agg(*(F.sum(s).alias(f"{s}_of") for s in sides), F.count(F.lit(1)).alias("size"))
    full = ending.join(F.broadcast(whole), F.lit(True))  # one row
    known = full.select("gram", *(((F.col(s) + k * (1.0 / F.col("size"))) / (F.col(f"{s}_of") + k)).alias(f"p_{s}") for s in sides))

    for j in range(1, order + 1):
        ending = grams.groupBy(F.substring("gram", order + 1 - j, j + 1).alias("gram")).agg(*sums) if j < order else grams
        context = Window.partitionBy(F.substring("gram", 1, j))
        ending = ending.select("*", *(F.sum(s).over(context).alias(f"{s}_of") for s in sides), F.substring("gram", 2, j).alias("shorter"))
        both = ending.join(known.withColumnRenamed("gram", "shorter"), "shorter")
        chances = [((F.col(s) + k * F.col(f"p_{s}")) / (F.col(f"{s}_of") + k)).alias(f"p_{s}") for s in sides]
        known = both.select("gram", *(["seen"] if j == order else []), *chances)
    return known.select("gram", "seen", F.round((F.log("p_allow") - F.log("p_block")) * 1_000_000).cast("long").alias("weight"))


def mean_ratios(lines: DataFrame, model: DataFrame, order: int = ORDER) -> DataFrame:
    """(line_id, score): log-likelihood difference over the number of characters and the end, in millionths, rounded down.

    `lines` has `line_id` and `line`. Frequent strings (see HEAVY) find their weights by broadcast, the others by a join on the string."""
    total = model.agg(F.sum("seen").alias("total"))
    often = F.broadcast(stash(model.join(F.broadcast(total), F.expr(f"seen * {HEAVY} >= total")).select("gram", "weight")))
    each = positions(lines.select("line_id", "line"), order)
    rare = each.join(often, "gram", "left_anti").join(model.select("gram", "weight"), "gram")
    found = each.join(often, "gram").unionByName(rare)
    sums = found.groupBy("line_id").agg(F.sum("weight").alias("sum"), F.count(F.lit(1)).alias("n"))
    return sums.select("line_id", F.floor(F.col("sum") / F.col("n")).cast("long").alias("score"))


def judge_urls(pages: DataFrame, rules=RULES, page_id: str = "page_id", url: str = "url", order: int = ORDER) -> DataFrame:
    """One row per row of `pages`: page_id, host, path, rule, verdict.

    A null URL, and one without `://`, has an empty host and path and is judged by the models as an empty URL. Where the
    rules judge no URL of one class, that class's model is uniform and its mean counts as 0. Repeated rows are
    judged alike, an empty table gives an empty result, other columns are ignored."""
    parsed = pages.select(F.col(page_id).alias("page_id"), host_of(F.col(url)).alias("host"), path_of(F.col(url)).alias("path"))
    rule, verdict = by_rules(F.col("host"), F.col("path"), rules)
    parsed = parsed.select("*", rule.alias("rule"), verdict.alias("ruled"), framed(F.col("host"), F.col("path"), order).alias("line"))
    says = lambda v: F.count(F.when(F.col("ruled") == v, 1))
    counted = parsed.groupBy("line").agg(
        says("allow").alias("allow"), says("block").alias("block"), F.count(F.when(F.col("ruled").isNull(), 1)).alias("open")
    )
    lines = stash(counted.withColumn("line_id", F.monotonically_increasing_id()))
    scores = mean_ratios(lines, stash(log_ratios(lines, order)), order)
    scored = stash(lines.join(scores, "line_id"))
    means = [F.coalesce(F.sum(F.col(s) * F.col("score")) / F.sum(s), F.lit(0.0)) for s in ("allow", "block")]
    threshold = scored.filter("allow + block > 0").agg(((means[0] + means[1]) / 2).alias("threshold"))
    by_model = scored.filter("open > 0").select("line", F.when(F.col("score") >= threshold.scalar(), "allow").otherwise("block").alias("modelled"))
    open_rows = parsed.filter("ruled is null").join(by_model, "line").select("page_id", "host", "path", "rule", F.col("modelled").alias("verdict"))
    return parsed.filter("ruled is not null").select("page_id", "host", "path", "rule", F.col("ruled").alias("verdict")).unionByName(open_rows)


def oracle(rules=RULES, order: int = ORDER, smoothing: int = SMOOTHING) -> str:
    """The same in SQL, written from the definitions: one table of counts for every length of context, joined per URL."""
    ordered = sorted(rules, key=lambda r: (-len(r[1] + r[2]), r))
    fits = lambda h, p: f"((host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}'))"
    pick = lambda f: "CASE " + " ".join(f"WHEN {fits(h, p)} THEN '{f(v, h, p)}'" for v, h, p in ordered) + " END"
    k = f"CAST({smoothing} AS DOUBLE)"
    models = []
    for j in range(order + 1):
        chance = lambda s: f"(c.{s} + {k} * b.p_{s}) / (o.{s} + {k}) AS p_{s}"  # noqa: B023, E731
        counts = "CAST(sum(allow) AS DOUBLE) AS allow, CAST(sum(block) AS DOUBLE) AS block"
        shorter = f"t{j - 1} b ON b.gram = substring(c.gram, 2)" if j else "t b ON true"
        models += [
            f"c{j} AS (SELECT substring(gram, {order + 1 - j}) AS gram, {counts} FROM g GROUP BY 1)",
            f"o{j} AS (SELECT substring(gram, {order + 1 - j}, {j}) AS context, {counts} FROM g GROUP BY 1)",
            f"t{j} AS (SELECT c.gram, {chance('allow')}, {chance('block')} FROM c{j} c JOIN o{j} o ON o.context = substring(c.gram, 1, {j}) JOIN {shorter})",
        ]
    base = "t AS (SELECT CAST(1 AS DOUBLE) / count(DISTINCT right(gram, 1)) AS p_allow, CAST(1 AS DOUBLE) / count(DISTINCT right(gram, 1)) AS p_block FROM g)"
    return f"""
WITH h AS (SELECT page_id, translate(coalesce(regexp_extract(url, '://([^/?#]*)', 1), ''), '{UPPER}', '{LOWER}') AS host,
                  coalesce(regexp_extract(url, '://[^/?#]*([^?#]*)', 1), '') AS path FROM pages),
p AS (SELECT *, {pick(lambda v, h, p: h + p)} AS rule, {pick(lambda v, h, p: v)} AS ruled,
             repeat(chr({START}), {order}) || host || path || chr({END}) AS line FROM h),
l AS (SELECT line, count(*) FILTER (WHERE ruled = 'allow') AS allow, count(*) FILTER (WHERE ruled = 'block') AS block FROM p GROUP BY line),
g AS (SELECT line, allow, block, substring(line, i.i, {order + 1}) AS gram FROM l, unnest(range(1, length(line) - {order - 1})) AS i(i)),
{base},
{", ".join(models)},
m AS (SELECT gram, CAST(round((ln(p_allow) - ln(p_block)) * 1000000) AS BIGINT) AS weight FROM t{order}),
s AS (SELECT g.line, CAST(floor(CAST(sum(weight) AS DOUBLE) / count(*)) AS BIGINT) AS score FROM g JOIN m USING (gram) GROUP BY g.line),
e AS (SELECT (coalesce(sum(allow * score) / sum(allow), 0) + coalesce(sum(block * score) / sum(block), 0)) / 2 AS threshold FROM l JOIN s USING (line) WHERE allow + block > 0)
SELECT page_id, host, path, rule, coalesce(ruled, CASE WHEN score >= threshold THEN 'allow' ELSE 'block' END) AS verdict
FROM p JOIN s USING (line), e
"""
