"""URL filter by empirical-Bayes host reputation, in DataFrame expressions.

Labelled pages give every host a number of outcomes and of bad ones.  Beta-binomial priors
shrink them level by level: a suffix towards all pages, a registered domain towards its
suffix, a host towards its domain.  The strength of each level's prior is the moment
estimate of how much the rates of the level's groups differ beyond chance.  A host whose
bad rate exceeds ``most_bad`` with a posterior probability of ``SURE`` (so the lower bound of its beta
posterior lies above) is blocked.
Explicit rules of host and path come first; the longest that fits decides.

Null urls, and urls without ``://``, have empty host and path and no rule; the empty host
is judged like any other.  Every page gives a row; labels of unknown pages are unused;
several labels of a page all count, and so does each of several rows of a page.  Without
labels no host is blocked.  No part runs in Python; pages of one host are dealt over
``SALTS`` groups where they meet its verdict, so a hot host is no hot task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Fixed values: (host, path, verdict) of the explicit rules.
RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))
# Second-level names under which domains are registered in country suffixes.
SECOND_LEVEL = ("co", "com", "org", "net", "ac", "gov", "edu", "or", "ne", "go")
MOST_BAD, SURE, SALTS = 0.5, 0.95, 16
#: Cells of the sum over a beta posterior, and its reach in standard deviations on either side.
CELLS, REACH = 400, 12
LOW_RHO, HIGH_RHO, NO_RHO = 0.001, 0.5, 0.05


def lowered(c: Column) -> Column:
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def host_and_path(url: Column) -> tuple[Column, Column]:
    at = F.coalesce(F.instr(url, "://"), F.lit(0))
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    return lowered(F.regexp_extract(rest, "^[^/?#]*", 0)), F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)


def domain_and_suffix(host: Column) -> tuple[Column, Column]:
    """Registered domain and public suffix; ports and user names do not count, addresses are their own domain."""
    bare = F.regexp_replace(host, r"^.*@|:[0-9]*$", "")
    names = F.split(bare, r"\.")
    n = F.size(names)
    country = (n >= 3) & (F.length(F.get(names, n - 1)) == 2) & F.get(names, n - 2).isin(*SECOND_LEVEL)
    kept = F.when(country, 2).otherwise(1)
    address = bare.rlike(r"^[0-9.]+$|^\[")
    suffix = F.when(address, F.lit("")).otherwise(F.concat_ws(".", F.slice(names, F.greatest(n - kept + 1, F.lit(1)), kept)))
    domain = F.when(address, bare).otherwise(F.concat_ws(".", F.slice(names, F.greatest(n - kept, F.lit(1)), kept + 1)))
    return domain, suffix


def rule_of(host: Column, path: Column, rules=RULES) -> Column:
    """The longest rule whose host is ``host`` or a parent of it and whose path starts ``path``: struct(len, rule, verdict) or null."""
    table: dict[str, list] = {}
    for h, p, verdict in rules:
        table.setdefault(h, []).append(F.struct(F.lit(len(h + p)).alias("len"), F.lit(h + p).alias("rule"), F.lit(verdict).alias("verdict"), F.lit(p).alias("path")))
    if not table:
        return F.lit(None).cast("struct<len:int,rule:string,verdict:string,path:string>")
    held = F.create_map(*[x for h, r in table.items() for x in (F.lit(h), F.array(*r))])
    deepest = max(h.count(".") for h in table) + 1  # labels; longer parents of a host fit no rule
    names = F.split(host, r"\.")
    parents = F.transform(F.sequence(F.greatest(F.lit(1), F.size(names) - (deepest - 1)), F.size(names)), lambda i: F.concat_ws(".", F.slice(names, i, F.size(names))))
    found = F.flatten(F.filter(F.transform(parents, lambda p: F.try_element_at(held, p)), lambda r: r.isNotNull()))
    return F.array_max(F.filter(found, lambda r: F.startswith(path, r["path"])))


def _strength(groups: DataFrame, prefix: str) -> DataFrame:
    """One row: strength of the prior over these groups (n outcomes, k bad each), by the moment estimate."""
    some = groups.where("n > 0")
    sums = some.agg(F.count("*").alias("m"), F.sum("n").alias("N"), F.sum("k").alias("K"), F.sum(F.col("n") * F.col("n")).alias("Q"), F.sum(F.col("k") * F.col("k") / F.col("n")).alias("W"))
    rho = F.expr("(W - K * K / N - (m - 1) * (K / N) * (1 - K / N)) / nullif((K / N) * (1 - K / N) * (N - Q / N - (m - 1)), 0)")
    bounded = F.when(F.col("N") > 0, F.least(F.greatest(rho, F.lit(LOW_RHO)), F.lit(HIGH_RHO)))
    return sums.select((1 / F.coalesce(bounded, F.lit(NO_RHO)) - 1).alias(f"{prefix}_strength"))


def exceeds(alpha: Column, beta: Column, bound: float) -> Column:
    """Probability that a beta variable lies above ``bound``: a sum over cells around its mean."""
    total = alpha + beta
    mean, sd = alpha / total, F.sqrt(alpha * beta / (total * total * (total + 1)))
    low, high = F.greatest(F.lit(0.0), mean - REACH * sd), F.least(F.lit(1.0), mean + REACH * sd)
    shape = F.struct(alpha.alias("a"), beta.alias("b"), mean.alias("m"), low.alias("low"), ((high - low) / CELLS).alias("h"))

    def cells(x: Column) -> Column:
        def weight(i: Column) -> Column:
            t = x["low"] + (i + 0.5) * x["h"]
            return F.exp((x["a"] - 1) * (F.ln(t) - F.ln(x["m"])) + (x["b"] - 1) * (F.ln(1 - t) - F.ln(1 - x["m"])))

        def above(i: Column) -> Column:
            return F.least(F.greatest((x["low"] + (i + 1.0) * x["h"] - bound) / x["h"], F.lit(0.0)), F.lit(1.0))

        weights = F.transform(F.sequence(F.lit(0), F.lit(CELLS - 1)), lambda i: F.struct(weight(i).alias("w"), above(i).alias("f")))
        sums = F.aggregate(weights, F.struct(F.lit(0.0).alias("all"), F.lit(0.0).alias("up")), lambda s, c: F.struct((s["all"] + c["w"]).alias("all"), (s["up"] + c["w"] * c["f"]).alias("up")))
        return F.get(F.transform(F.array(sums), lambda s: s["up"] / s["all"]), F.lit(0))

    return F.get(F.transform(F.array(shape), cells), F.lit(0))


def posteriors(hosts: DataFrame) -> DataFrame:
    """host, n, k -> also alpha, beta and mean of its bad rate's posterior."""
    domain, suffix = domain_and_suffix(F.col("host"))
    hosts = hosts.select("host", "n", "k", domain.alias("domain"), suffix.alias("suffix"))
    domains = hosts.groupBy("domain", "suffix").agg(F.sum("n").alias("n"), F.sum("k").alias("k"))
    suffixes = domains.groupBy("suffix").agg(F.sum("n").alias("n"), F.sum("k").alias("k"))
    total = suffixes.agg(((F.sum("k") + 0.5) / (F.sum("n") + 1)).alias("all_mean"))

    def shrunk(groups: DataFrame, prefix: str, above: str) -> DataFrame:
        strength = F.broadcast(_strength(groups, prefix))  # one row
        a = F.col(above) * F.col(f"{prefix}_strength") + F.col("k")
        b = (1 - F.col(above)) * F.col(f"{prefix}_strength") + F.col("n") - F.col("k")
        return groups.join(strength).withColumn("alpha", a).withColumn("beta", b).withColumn(f"{prefix}_mean", F.col("alpha") / (F.col("alpha") + F.col("beta")))

    s = shrunk(suffixes.join(F.broadcast(total)), "suffix", "all_mean").select("suffix", "suffix_mean")
    d = shrunk(domains.join(s, "suffix"), "domain", "suffix_mean").select("domain", "suffix", "domain_mean")
    h = shrunk(hosts.join(d, ["domain", "suffix"]), "host", "domain_mean")
    return h.select("host", "domain", "suffix", "n", "k", "alpha", "beta", F.col("host_mean").alias("mean"))


def judge(pages: DataFrame, outcomes: DataFrame, rules=RULES, most_bad: float = MOST_BAD) -> DataFrame:
    """Per page: page_id, host, path, rule, verdict.  ``outcomes`` has page_id and bad (boolean)."""
    host, path = host_and_path(F.col("url"))
    rows = pages.select(F.col("page_id").cast("long"), host.alias("host"), path.alias("path"))
    found = outcomes.where("page_id is not null and bad is not null").groupBy(F.col("page_id").cast("long").alias("page_id")).agg(F.count("*").alias("n"), F.sum(F.col("bad").cast("long")).alias("k"))
    counted = rows.select("page_id", "host").join(found, "page_id", "left").groupBy("host").agg(F.sum(F.coalesce("n", F.lit(0))).alias("n"), F.sum(F.coalesce("k", F.lit(0))).alias("k"))
    likely = posteriors(counted).where(F.col("mean") > most_bad)  # a cheap condition first: few hosts are summed over
    bad = likely.where(exceeds(F.col("alpha"), F.col("beta"), most_bad) >= SURE).select(F.col("host").alias("bad_host"))
    bad = bad.withColumn("bad_salt", F.explode(F.array(*[F.lit(i) for i in range(SALTS)])))
    salt = F.pmod(F.xxhash64("page_id", "path"), F.lit(SALTS)).cast("int")
    rows = rows.withColumn("salt", salt).withColumn("r", rule_of(F.col("host"), F.col("path"), rules))
    joined = rows.join(bad, (F.col("host") == F.col("bad_host")) & (F.col("salt") == F.col("bad_salt")), "left")
    method = F.when(F.col("bad_host").isNotNull(), "block").otherwise("allow")
    return joined.select("page_id", "host", "path", F.col("r.rule").alias("rule"), F.coalesce("r.verdict", method).alias("verdict"))


def label_outcomes(labels: DataFrame, pages: DataFrame) -> DataFrame:
    """page_id, bad: outcomes of the document that a page shows, which is the last number in its url's path.

    Bad is low quality or toxic.  Pages without such a number, and documents without a label, have no outcome.
    """
    number = F.regexp_extract(host_and_path(F.col("url"))[1], "/([0-9]{1,18})[^/0-9]*/?$", 1)
    shown = pages.select(F.col("page_id").cast("long").alias("page_id"), F.when(number != "", number).cast("long").alias("shown"))
    bad = F.when(F.col("quality").isNotNull() | F.col("toxic").isNotNull(), F.coalesce(F.col("quality") == 0, F.lit(False)) | F.coalesce(F.col("toxic") == 1, F.lit(False)))
    known = labels.select(F.col("doc_id").cast("long").alias("shown"), bad.alias("bad")).where("shown is not null and bad is not null")
    return shown.where("shown is not null").join(known, "shown").select("page_id", "bad")


ORACLE = r"""
WITH u AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
p AS (SELECT CAST(page_id AS BIGINT) AS page_id, translate(regexp_extract(rest, '^[^/?#]*', 0), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
             regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM u),
sh AS (SELECT page_id, TRY_CAST(nullif(regexp_extract(path, '/([0-9]{1,18})[^/0-9]*/?$', 1), '') AS BIGINT) AS shown FROM p),
o AS (SELECT page_id, count(*) AS n, CAST(sum(CAST(coalesce(quality = 0, false) OR coalesce(toxic = 1, false) AS INT)) AS BIGINT) AS k
      FROM sh JOIN labels ON shown = doc_id WHERE page_id IS NOT NULL AND (quality IS NOT NULL OR toxic IS NOT NULL) GROUP BY 1),
h AS (SELECT host, sum(coalesce(n, 0)) AS n, sum(coalesce(k, 0)) AS k, string_split(regexp_replace(host, '^.*@|:[0-9]*$', '', 'g'), '.') AS a FROM p LEFT JOIN o USING (page_id) GROUP BY host),
hd AS (SELECT host, n, k, CASE WHEN len(a) >= 3 AND length(a[-1]) = 2 AND a[-2] IN ('co','com','org','net','ac','gov','edu','or','ne','go') THEN 2 ELSE 1 END AS c, a,
       regexp_matches(array_to_string(a, '.'), '^[0-9.]+$|^\[') AS address FROM h),
hh AS (SELECT host, n, k, CASE WHEN address THEN '' ELSE array_to_string(a[greatest(len(a) - c + 1, 1):], '.') END AS suffix,
              CASE WHEN address THEN array_to_string(a, '.') ELSE array_to_string(a[greatest(len(a) - c, 1):], '.') END AS domain FROM hd),
dd AS (SELECT domain, suffix, sum(n) AS n, sum(k) AS k FROM hh GROUP BY ALL),
ss AS (SELECT suffix, sum(n) AS n, sum(k) AS k FROM dd GROUP BY ALL),
g AS (SELECT 's' AS level, n::DOUBLE AS n, k::DOUBLE AS k FROM ss UNION ALL SELECT 'd', n, k FROM dd UNION ALL SELECT 'h', n, k FROM hh),
m AS (SELECT level, count(*) AS m, sum(n) AS N1, sum(k) AS K1, sum(n * n) AS Q, sum(k * k / n) AS W FROM g WHERE n > 0 GROUP BY level),
r AS (SELECT level, 1 / coalesce(least(greatest((W - K1 * K1 / N1 - (m - 1) * (K1 / N1) * (1 - K1 / N1)) / nullif((K1 / N1) * (1 - K1 / N1) * (N1 - Q / N1 - (m - 1)), 0), 0.001), 0.5), 0.05) - 1 AS st FROM m),
st AS (SELECT coalesce(max(st) FILTER (level = 's'), 19) AS s, coalesce(max(st) FILTER (level = 'd'), 19) AS d, coalesce(max(st) FILTER (level = 'h'), 19) AS h FROM r),
t AS (SELECT (sum(k) + 0.5) / (sum(n) + 1) AS mean FROM ss),
sm AS (SELECT suffix, (t.mean * st.s + k) / (st.s + n) AS mean FROM ss, t, st),
dm AS (SELECT domain, dd.suffix, (sm.mean * st.d + k) / (st.d + n) AS mean FROM dd JOIN sm ON dd.suffix = sm.suffix, st),
hm AS (SELECT host, dm.mean * st.h + k AS a, (1 - dm.mean) * st.h + n - k AS b FROM hh JOIN dm ON hh.domain = dm.domain AND hh.suffix = dm.suffix, st),
sd AS (SELECT host, a, b, a / (a + b) AS m, sqrt(a * b / ((a + b) * (a + b) * (a + b + 1))) AS sd FROM hm WHERE a / (a + b) > 0.5),
gr AS (SELECT *, greatest(0, m - 12 * sd) AS low, (least(1, m + 12 * sd) - greatest(0, m - 12 * sd)) / 400 AS ce FROM sd),
ce AS (SELECT host, ce, low + i * ce AS lo, exp((a - 1) * (ln(low + (i + 0.5) * ce) - ln(m)) + (b - 1) * (ln(1 - low - (i + 0.5) * ce) - ln(1 - m))) AS w FROM gr, generate_series(0, 399) t(i)),
bad AS (SELECT host FROM ce GROUP BY host HAVING sum(w * least(greatest((lo + ce - 0.5) / ce, 0), 1)) / sum(w) >= 0.95),
f AS (SELECT p.*, CASE WHEN (host = 'example.net' OR host LIKE '%.example.net') AND starts_with(path, '/en/') THEN 'example.net/en/'
                       WHEN (host = 'example.com' OR host LIKE '%.example.com') AND starts_with(path, '/de/') THEN 'example.com/de/'
                       WHEN (host = 'org' OR host LIKE '%.org') AND starts_with(path, '/fr/') THEN 'org/fr/'
                       WHEN (host = 'net' OR host LIKE '%.net') AND starts_with(path, '/') THEN 'net/' END AS rule FROM p)
SELECT page_id, host, path, rule,
       CASE WHEN rule IN ('net/', 'example.com/de/') THEN 'block' WHEN rule IS NOT NULL THEN 'allow' WHEN host IN (SELECT host FROM bad) THEN 'block' ELSE 'allow' END AS verdict
FROM f"""
