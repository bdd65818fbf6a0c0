"""URL filter: prefix rules first, then a character language-model ratio.

URLs that a rule decides train two smoothed variable-order Markov models, one of accepted and one of
rejected URLs. A character's probability starts uniform and is refined by every longer context seen in
training: p = (count + WEIGHT * p_shorter) / (total + WEIGHT). A URL's score is its log-likelihood
difference per character; the limit is calibrated on labelled URLs held out from training. The two
models are fitted on all other labelled URLs and hold contexts with at least ``LEAST`` occurrences, so
their size is bounded by the contexts that occur; contexts of a length are broadcast while they are few.

Scores are sums of whole millionths, so no order of summation changes a verdict. Everything is
DataFrame functions; equal (host, path) pairs are scored once and joined back.

Cases: a null url or one without :// has an empty host and path and takes the models' verdict of an
empty string; null ids and repeated rows are judged each; without labelled URLs of both classes the
verdict is allow; empty tables give empty results; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..runtime.scratch import save

ORDERS, WEIGHT, LEAST, UNIFORM = 4, 2.0, 4, 1 / 96
SAMPLE, BROADCAST_CONTEXTS = 20_000, 200_000
BEFORE, AFTER = "\x02", "\x03"
GRID = 50_000


@dataclass(frozen=True)
class UrlRule:
    verdict: str
    host: str
    path: str

    @property
    def name(self) -> str:
        return self.host + self.path


#: The rules of the query.
RULES = (UrlRule("allow", "com", "/"), UrlRule("block", "example.com", "/en/"), UrlRule("allow", "www.example.com", "/en/"), UrlRule("block", "net", "/es/"), UrlRule("block", "net", "/fr/"))


def with_rule(pages: DataFrame, rules: tuple[UrlRule, ...] = RULES, url_col: str = "url") -> DataFrame:
    """Add host, path, rule and label (the rule's verdict) to rows of ``pages``."""
    parts = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    url = F.coalesce(F.col(url_col).cast("string"), F.lit(""))
    found = pages.withColumn("host", F.translate(F.regexp_extract(url, parts, 1), upper, upper.lower())).withColumn("path", F.regexp_extract(url, parts, 2))
    rule = label = F.lit(None).cast("string")
    for r in sorted(rules, key=lambda r: (len(r.name), r.name)):
        fits = ((F.col("host") == r.host) | F.col("host").endswith("." + r.host)) & F.col("path").startswith(r.path)
        rule, label = F.when(fits, F.lit(r.name)).otherwise(rule), F.when(fits, F.lit(r.verdict)).otherwise(label)
    return found.withColumn("rule", rule).withColumn("label", label)


def positions(urls: DataFrame) -> DataFrame:
    """One row per character of (host, path) and its end mark: the character and its contexts c0, c1, ..."""
    padded = urls.withColumn("_s", F.concat(F.lit(BEFORE * (ORDERS - 1)), "host", "path", F.lit(AFTER)))
    at = padded.withColumn("_i", F.explode(F.sequence(F.lit(ORDERS), F.length("_s"))))
    contexts = {f"c{k}": F.substring("_s", F.col("_i") - k, F.lit(k)) for k in range(ORDERS)}
    return at.withColumns(contexts).withColumn("ch", F.substring("_s", F.col("_i"), F.lit(1))).drop("_s", "_i")


def fit(labelled: DataFrame) -> DataFrame:
    """Contexts with their totals per class and the counts of next characters."""
    grams = positions(labelled).select(F.explode(F.array(*(f"c{k}" for k in range(ORDERS)))).alias("context"), "ch", (F.col("label") == "allow").cast("long").alias("a"))
    counts = grams.groupBy("context", "ch").agg(F.sum("a").alias("a"), F.sum(1 - F.col("a")).alias("r"))
    entry = F.struct("ch", F.struct("a", "r"))
    model = counts.groupBy("context").agg(F.sum("a").alias("a"), F.sum("r").alias("r"), F.map_from_entries(F.sort_array(F.collect_list(entry))).alias("next"))
    return model.where(F.col("a") + F.col("r") >= LEAST)


def score(urls: DataFrame, model: DataFrame, small: set[int]) -> DataFrame:
    """(host, path, score): log-likelihood difference in millionths per character, for distinct urls.

    ``small`` are the lengths of contexts that are few enough to be broadcast.
    """
    rows = positions(urls.select("host", "path"))
    p = {"a": F.lit(UNIFORM), "r": F.lit(UNIFORM)}
    for k in range(ORDERS):
        named = model.where(F.length("context") == k).select(F.col("context").alias(f"c{k}"), F.struct("a", "r", "next").alias(f"m{k}"))
        rows = rows.join(F.broadcast(named) if k in small else named, f"c{k}", "left")
        seen = F.try_element_at(F.col(f"m{k}.next"), F.col("ch"))
        for side in p:
            total = F.coalesce(F.col(f"m{k}.{side}"), F.lit(0))
            p[side] = ((F.coalesce(seen[side], F.lit(0)) + WEIGHT * p[side]) / (total + WEIGHT)).alias(f"p{side}")
        rows = rows.select("host", "path", "ch", *(f"c{j}" for j in range(k + 1, ORDERS)), *(p[s].alias(f"{s}{k}") for s in p))
        p = {s: F.col(f"{s}{k}") for s in p}
    gain = F.round(1e6 * F.ln(p["a"] / p["r"])).cast("long")
    return rows.groupBy("host", "path").agg(F.sum(gain).alias("s"), F.count("*").alias("n")).select("host", "path", F.expr("s div n").alias("score"))


def calibrate(scored: DataFrame) -> int:
    """The limit with the least sum of both classes' error rates on (label, score); 0 without both classes."""
    bucket = F.floor(F.col("score") / GRID).cast("long")
    bins = scored.groupBy(F.least(F.greatest(bucket, F.lit(-200)), F.lit(200)).alias("bin")).agg(F.sum((F.col("label") == "allow").cast("long")).alias("a"), F.sum((F.col("label") == "block").cast("long")).alias("r"))
    rows = sorted((r["bin"], r["a"], r["r"]) for r in bins.collect())  # at most 401 rows
    all_a, all_r = sum(r[1] for r in rows), sum(r[2] for r in rows)
    if not all_a or not all_r:
        return 0
    best, limit, a, r = None, 0, 0, 0
    for at, n_a, n_r in [*rows, (rows[-1][0] + 1, 0, 0)]:
        error = a / all_a + (all_r - r) / all_r
        if best is None or error < best:
            best, limit = error, at * GRID
        a, r = a + n_a, r + n_r
    return limit


def judge_urls(pages: DataFrame, rules: tuple[UrlRule, ...] = RULES, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """(id, host, path, rule, verdict, score) of every row; the score is null where a rule decides."""
    ruled = with_rule(pages.select(F.col(id_col).alias("id"), F.col(url_col).alias("_url")), rules, "_url").drop("_url")
    order = F.conv(F.substring(F.md5(F.concat_ws("\n", "host", "path")), 1, 8), 16, 10).cast("long")
    train = save(ruled.where("label IS NOT NULL").select("label", "host", "path").distinct(), "url_labelled")
    held = F.pmod(order, F.lit(5)) == 0
    model = save(fit(train.where(~held)), "url_model")
    sizes = {r["k"]: r["count"] for r in model.groupBy(F.length("context").alias("k")).count().collect()}  # ORDERS rows
    small = {k for k in range(ORDERS) if sizes.get(k, 0) <= BROADCAST_CONTEXTS}
    both = train.agg(F.countDistinct("label")).first()[0] == 2
    tested = train.where(held).join(score(train.where(held), model, small), ["host", "path"])
    limit = calibrate(tested) if both else None
    rest = ruled.where("label IS NULL").select("host", "path").distinct()
    scores = score(rest, model, small)
    keys = [ruled[c] == scores[c] for c in ("host", "path")]
    joined = ruled.join(scores, [*keys, ruled["label"].isNull()], "left").select(ruled["*"], scores["score"])
    by_model = F.when(F.col("score") >= limit, "allow").otherwise("block") if both else F.lit("allow")
    return joined.select(F.col("id").alias(id_col), "host", "path", "rule", F.coalesce("label", by_model).alias("verdict"), "score")


def oracle(rules: tuple[UrlRule, ...] = RULES, sample: int = SAMPLE) -> str:
    """DuckDB SQL for :func:`judge_urls` over ``pages`` with at most ``sample`` distinct labelled URLs per class."""
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    part = lambda n: rf"regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)([^?#]*)', {n})"
    fits = lambda r: f"(host = '{r.host}' OR ends_with(host, '.{r.host}')) AND starts_with(path, '{r.path}')"
    longest = sorted(rules, key=lambda r: (len(r.name), r.name), reverse=True)
    case = lambda value: "CASE " + " ".join(f"WHEN {fits(r)} THEN '{value(r)}'" for r in longest) + " END"
    cut = ", ".join(f"substr(s, i - {k}, {k}) AS c{k}" for k in range(ORDERS))
    at = lambda source: f"SELECT *, {cut}, substr(s, i, 1) AS ch FROM (SELECT *, unnest(range({ORDERS}, len(s) + 1)) AS i FROM (SELECT *, repeat(chr({ord(BEFORE)}), {ORDERS - 1}) || host || path || chr({ord(AFTER)}) AS s FROM {source}))"
    joins = " ".join(f"LEFT JOIN m m{k} ON m{k}.context = c{k} LEFT JOIN g g{k} ON g{k}.context = c{k} AND g{k}.ch = q.ch" for k in range(ORDERS))
    p = {"a": f"{UNIFORM!r}::DOUBLE", "r": f"{UNIFORM!r}::DOUBLE"}
    for k in range(ORDERS):
        p = {x: f"((coalesce(g{k}.{x}, 0) + {WEIGHT}::DOUBLE * {p[x]}) / (coalesce(m{k}.{x}, 0) + {WEIGHT}::DOUBLE))" for x in p}
    scored = lambda source: f"SELECT host, path, (sign(sum(v)) * (abs(sum(v)) // count(*)))::BIGINT AS score FROM (SELECT host, path, round(1e6 * ln({p['a']} / {p['r']}))::BIGINT AS v FROM ({at(source)}) q {joins}) GROUP BY host, path"
    return f"""
WITH f AS MATERIALIZED (SELECT page_id, translate({part(1)}, '{upper}', '{upper.lower()}') AS host, {part(2)} AS path FROM pages),
u AS MATERIALIZED (SELECT *, {case(lambda r: r.name)} AS rule, {case(lambda r: r.verdict)} AS label FROM f),
o AS (SELECT *, ('0x' || substr(md5(host || chr(10) || path), 1, 8))::BIGINT AS k FROM (SELECT DISTINCT label, host, path FROM u WHERE label IS NOT NULL)),
t AS MATERIALIZED (SELECT label, host, path, k % 5 = 0 AS held FROM (SELECT *, row_number() OVER (PARTITION BY label ORDER BY k, host, path) AS n FROM o) WHERE n <= {sample}),
c AS (SELECT unnest([{', '.join(f'c{k}' for k in range(ORDERS))}]) AS context, ch, label = 'allow' AS a FROM ({at('(SELECT * FROM t WHERE NOT held)')})),
x AS MATERIALIZED (SELECT context, ch, count(*) FILTER (a) AS a, count(*) FILTER (NOT a) AS r FROM c GROUP BY 1, 2),
m AS MATERIALIZED (SELECT context, sum(a) AS a, sum(r) AS r FROM x GROUP BY 1 HAVING sum(a) + sum(r) >= {LEAST}),
g AS MATERIALIZED (SELECT x.* FROM x JOIN m USING (context)),
h AS (SELECT greatest(-200, least(200, floor(score / {GRID})))::BIGINT AS bin, label FROM ({scored('(SELECT host, path FROM t WHERE held)')}) JOIN t USING (host, path)),
b AS (SELECT bin, count(*) FILTER (label = 'allow') AS a, count(*) FILTER (label = 'block') AS r FROM h GROUP BY bin UNION ALL SELECT max(bin) + 1, 0, 0 FROM h),
w AS (SELECT bin, coalesce(sum(a) OVER z, 0) AS a, coalesce(sum(r) OVER z, 0) AS r, (SELECT sum(a) FROM b) AS aa, (SELECT sum(r) FROM b) AS rr FROM b WINDOW z AS (ORDER BY bin ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
l AS (SELECT coalesce((SELECT bin * {GRID} FROM w WHERE aa > 0 AND rr > 0 ORDER BY a / aa + (rr - r) / rr, bin LIMIT 1), 0) AS lim, (SELECT count(DISTINCT label) FROM t) = 2 AS both_seen),
e AS MATERIALIZED ({scored('(SELECT DISTINCT host, path FROM u WHERE label IS NULL)')})
SELECT page_id, u.host, u.path, rule, coalesce(label, CASE WHEN NOT both_seen OR score >= lim THEN 'allow' ELSE 'block' END) AS verdict, score
FROM u LEFT JOIN e ON u.label IS NULL AND e.host = u.host AND e.path = u.path, l
"""
