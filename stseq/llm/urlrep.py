"""Host reputation by empirical Bayes, and a URL filter with explicit rules before it.

Labelled page outcomes (bad or not) are counted for each host. A host's bad rate gets a beta prior whose
mean is the shrunk rate of its registered domain, whose own prior mean is the shrunk rate of its suffix,
and that of the global rate; each prior weighs ``strength`` pages, estimated from the
spread of the hosts' rates (moments of the beta-binomial). A host is blocked if the lower bound of
its posterior (mean less ``z`` standard deviations) is above ``times`` the rate of all hosts (or above one half): only
what the evidence makes sure to be worse than usual is cut, however common bad pages are.
A host without labels is judged by its prior alone: of its domain, else its suffix, else the global rate.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stseq.llm.common import checked_small, stored

#: Explicit rules: (verdict, host and path prefix).
RULES = (("allow", "org/"), ("block", "example.org/es/"), ("block", "example.org/en/1"), ("allow", "com/fr/"), ("block", "com/de/"))
LEAST, MOST, Z, TIMES, LIMIT = 1.0, 1000.0, 1.645, 1.5, 0.5
#: Suffixes of two labels under which domains are registered.
PAIRED_SUFFIXES = (
    "co.uk org.uk ac.uk gov.uk me.uk com.au net.au org.au edu.au gov.au co.nz org.nz ac.nz co.jp ne.jp or.jp ac.jp go.jp com.br org.br gov.br com.mx org.mx "
    "co.in org.in ac.in gov.in co.za org.za ac.za com.cn org.cn edu.cn gov.cn com.tr org.tr co.kr or.kr com.tw org.tw com.hk com.sg com.my co.id co.th co.il com.ar com.co com.pl com.ua"
).split()
_URL = r"(?s)^.*?://([^/?#]*)([^?#]*)"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def url_host(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, _URL, 1), F.lit("")), _UPPER, _LOWER)


def url_path(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, _URL, 2), F.lit(""))


def bare_host(host: Column) -> Column:
    """The host without user and port."""
    return F.regexp_replace(F.substring_index(host, "@", -1), r":[0-9]*$", "")


def suffix(host: Column) -> Column:
    """The last label of the host, or the last two where domains are registered under such a pair; an address of numbers is whole."""
    bare = bare_host(host)
    pair = F.substring_index(bare, ".", -2)
    return F.when(bare.rlike(r"^[0-9.]+$|^\["), bare).when(pair.isin(*PAIRED_SUFFIXES), pair).otherwise(F.substring_index(bare, ".", -1))


def registered_domain(host: Column) -> Column:
    """The suffix and the label before it."""
    bare = bare_host(host)
    paired = F.substring_index(bare, ".", -2).isin(*PAIRED_SUFFIXES)
    return F.when(bare.rlike(r"^[0-9.]+$|^\["), bare).otherwise(F.when(paired, F.substring_index(bare, ".", -3)).otherwise(F.substring_index(bare, ".", -2)))


def rule_column(host: Column, path: Column, rules=RULES) -> Column:
    """The longest rule whose host is the url's host or a parent of it and whose path begins the url's; else null."""
    best = F.lit(None).cast("string")
    for _, rule in sorted(rules, key=lambda r: len(r[1])):
        name, _, rest = rule.partition("/")
        fits = ((host == name) | host.endswith("." + name)) & path.startswith("/" + rest)
        best = F.when(fits, F.lit(rule)).otherwise(best)
    return best


def prior_strength(hosts: DataFrame) -> tuple[float, float]:
    """Global bad rate and, by moments of the beta-binomial, how many pages a prior weighs (1 to 1000); one row reaches the driver."""
    t = hosts.agg(
        F.count("*").alias("m"), F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.coalesce(F.sum("k"), F.lit(0)).alias("k"),
        F.sum((F.col("n") * F.col("n")).cast("double")).alias("nn"), F.sum((F.col("k") * F.col("k")).cast("double") / F.col("n")).alias("kk"),
    ).first()
    n, k = float(t["n"]), float(t["k"])
    rate = (k + 1.0) / (n + 2.0)
    if t["m"] < 2 or not 0 < k < n:
        return rate, MOST
    p = k / n
    spread = t["kk"] - k * p  # sum of n_i * (p_i - p)^2
    room = n - t["nn"] / n - (t["m"] - 1)
    rho = (spread / (p * (1 - p)) - (t["m"] - 1)) / room if room > 0 else 0.0
    return rate, min(MOST, max(LEAST, (1 - rho) / rho)) if rho > 0 else MOST


def host_reputation(outcomes: DataFrame, strength: float | None = None, others: DataFrame | None = None) -> DataFrame:
    """Posterior of each host's bad rate from labelled outcomes (host, bad 0/1; rows with a null are left out).

    Columns: host, pages, bad_pages, prior_mean, rate (of all hosts), mean, sd. ``strength`` None: estimated from the hosts' spread.
    ``others`` (host): further hosts to judge; those without labels have 0 pages and their prior as posterior.
    Partial counts are taken before each exchange, so a host with a third of all rows is a handful of rows.
    """
    labelled = stored(outcomes.where("host is not null and bad is not null").groupBy("host").agg(F.count("*").alias("n"), F.sum("bad").alias("k")), "labelled-hosts")
    rate, found = prior_strength(labelled)
    k0 = F.lit(float(strength if strength is not None else found))
    levels = [registered_domain(F.col("host")).alias("domain"), suffix(F.col("host")).alias("suffix")]
    domains = labelled.select(*levels, "n", "k").groupBy("domain", "suffix").agg(F.sum("n").alias("dn"), F.sum("k").alias("dk"))
    s = domains.groupBy("suffix").agg(F.sum("dn").alias("sn"), F.sum("dk").alias("sk"))
    s = checked_small(s.select("suffix", ((F.col("sk") + k0 * F.lit(rate)) / (F.col("sn") + k0)).alias("s_mean")), "suffixes")
    d = domains.join(s, "suffix").select("domain", ((F.col("dk") + k0 * F.col("s_mean")) / (F.col("dn") + k0)).alias("d_mean"))
    hosts = labelled
    if others is not None:
        zero = F.lit(0).cast("bigint")
        more = others.where("host is not null").select("host").distinct().select("host", zero.alias("n"), zero.alias("k"))
        hosts = labelled.unionByName(more).groupBy("host").agg(F.sum("n").alias("n"), F.sum("k").alias("k"))
    hosts = hosts.select("host", *levels, "n", "k").join(d, "domain", "left").join(s, "suffix", "left")
    hosts = hosts.withColumn("prior_mean", F.coalesce("d_mean", "s_mean", F.lit(rate)))
    a = k0 * F.col("prior_mean") + F.col("k")
    b = k0 * (1 - F.col("prior_mean")) + F.col("n") - F.col("k")
    return hosts.select(
        "host", F.col("n").alias("pages"), F.col("k").alias("bad_pages"), "prior_mean",
        F.lit(rate).alias("rate"), F.try_divide(a, a + b).alias("mean"), F.sqrt(F.try_divide(a * b, (a + b) * (a + b) * (a + b + 1))).alias("sd"),
    )


def filter_urls(pages: DataFrame, outcomes: DataFrame, rules=RULES, strength: float | None = None, z: float = Z, times: float = TIMES, limit: float = LIMIT) -> DataFrame:
    """page_id, host, path, rule, verdict, posterior mean and lower bound for every row of ``pages``.

    Null or malformed urls have an empty host and path; a host without labels is judged by the prior of its domain,
    suffix or all hosts. Repeated rows stay.
    """
    seen = pages.select("page_id", url_host(F.col("url")).alias("host"), url_path(F.col("url")).alias("path"))
    known = host_reputation(outcomes, strength, seen.select("host"))
    known = known.select("host", F.col("mean").alias("bad_mean"), (F.col("mean") - F.lit(z) * F.col("sd")).alias("bad_low"), F.least(F.lit(limit), F.lit(times) * F.col("rate")).alias("bar"))
    rule = rule_column(F.col("host"), F.col("path"), rules)
    said = F.lit(None).cast("string")
    for verdict, text in rules:
        said = F.when(F.col("rule") == text, F.lit(verdict)).otherwise(said)
    return (
        seen.withColumn("rule", rule).join(known, "host", "left")
        .withColumn("verdict", F.coalesce(said, F.when(F.col("bad_low") > F.col("bar"), "block").otherwise("allow")))
        .select("page_id", "host", "path", "rule", "verdict", F.round("bad_mean", 9).alias("bad_mean"), F.round("bad_low", 9).alias("bad_low"))
    )


def labelled_outcomes(pages: DataFrame, labels: DataFrame) -> DataFrame:
    """Outcomes (host, bad) of the pages whose path ends in the number of a labelled document; bad: low quality or toxic."""
    number = F.regexp_extract(url_path(F.col("url")), r"/([0-9]{1,18})[^/0-9]*/?$", 1)
    seen = pages.select(url_host(F.col("url")).alias("host"), F.when(number != "", number.cast("long")).alias("doc_id")).where("doc_id is not null")
    marks = labels.where("doc_id is not null").groupBy("doc_id").agg(
        F.max(F.when((F.col("quality") == 0) | (F.col("toxic") == 1), 1).otherwise(0)).alias("bad")
    )
    return seen.join(marks, "doc_id").select("host", "bad")


def oracle_sql() -> str:
    """The verdicts and bounds of :func:`filter_urls` over pages and labels in DuckDB SQL."""
    pairs = ", ".join(f"'{p}'" for p in PAIRED_SUFFIXES)
    cases = {"rule": "", "said": ""}
    for verdict, rule in sorted(RULES, key=lambda r: -len(r[1])):
        name, _, rest = rule.partition("/")
        fits = f"(host = '{name}' OR ends_with(host, '.{name}')) AND starts_with(path, '/{rest}')"
        cases["rule"] += f" WHEN {fits} THEN '{rule}'"
        cases["said"] += f" WHEN {fits} THEN '{verdict}'"
    return f"""WITH cut AS (SELECT page_id, coalesce(regexp_extract(url, '^.*?://([^/?#]*)([^?#]*)', ['h', 'p'], 's'), {{'h': '', 'p': ''}}) AS u FROM pages),
 seen AS (SELECT page_id, translate(u.h, '{_UPPER}', '{_LOWER}') AS host, u.p AS path FROM cut),
 marks AS (SELECT doc_id, max(CASE WHEN quality = 0 OR toxic = 1 THEN 1 ELSE 0 END) AS bad FROM labels GROUP BY doc_id),
 outcomes AS (SELECT host, bad FROM (SELECT host, nullif(regexp_extract(path, '/([0-9]{{1,18}})[^/0-9]*/?$', 1), '')::BIGINT AS doc_id FROM seen) JOIN marks USING (doc_id)),
 lab AS (SELECT host, count(*) AS n, sum(bad) AS k FROM outcomes GROUP BY host),
 tot AS (SELECT count(*) AS m, sum(n)::DOUBLE AS n, sum(k)::DOUBLE AS k, sum(n::DOUBLE * n) AS nn, sum(k::DOUBLE * k / n) AS kk FROM lab),
 est AS (SELECT (k + 1) / (n + 2) AS rate, CASE WHEN m < 2 OR k <= 0 OR k >= n OR n - nn / n - (m - 1) <= 0 THEN 0 ELSE ((kk - k * k / n) / (k / n * (1 - k / n)) - (m - 1)) / (n - nn / n - (m - 1)) END AS rho FROM tot),
 par AS (SELECT rate, CASE WHEN rho > 0 THEN least({MOST}, greatest({LEAST}, (1 - rho) / rho)) ELSE {MOST}::DOUBLE END AS k0 FROM est),
 hosts AS (SELECT DISTINCT host FROM seen UNION SELECT host FROM lab),
 bare AS (SELECT host, regexp_replace(string_split(host, '@')[-1], ':[0-9]*$', '') AS b FROM hosts),
 part AS (SELECT host, b, regexp_matches(b, '^[0-9.]+$|^\\[') AS ip, string_split(b, '.') AS l FROM bare),
 lev AS (SELECT host, CASE WHEN ip THEN b WHEN array_to_string(l[-2:], '.') IN ({pairs}) THEN array_to_string(l[-2:], '.') ELSE l[-1] END AS suffix,
  CASE WHEN ip THEN b WHEN array_to_string(l[-2:], '.') IN ({pairs}) THEN array_to_string(l[-3:], '.') ELSE array_to_string(l[-2:], '.') END AS domain FROM part),
 dom AS (SELECT domain, suffix, sum(n) AS dn, sum(k) AS dk FROM lab JOIN lev USING (host) GROUP BY domain, suffix),
 suf AS (SELECT suffix, (sum(dk) + any_value(k0) * any_value(rate)) / (sum(dn) + any_value(k0)) AS s_mean FROM dom, par GROUP BY suffix),
 dm AS (SELECT domain, (dk + k0 * s_mean) / (dn + k0) AS d_mean FROM dom JOIN suf USING (suffix), par),
 post AS (SELECT lev.host, rate, k0 * coalesce(d_mean, s_mean, rate) + coalesce(k, 0) AS a, k0 * (1 - coalesce(d_mean, s_mean, rate)) + coalesce(n, 0) - coalesce(k, 0) AS b
  FROM lev LEFT JOIN lab USING (host) LEFT JOIN dm USING (domain) LEFT JOIN suf USING (suffix), par),
 known AS (SELECT host, rate, a / (a + b) AS bad_mean, a / (a + b) - {Z} * sqrt(a * b / ((a + b) * (a + b) * (a + b + 1))) AS bad_low FROM post)
SELECT page_id, host, path, CASE{cases['rule']} END AS rule, coalesce(CASE{cases['said']} END, CASE WHEN bad_low > least({LIMIT}, {TIMES} * rate) THEN 'block' ELSE 'allow' END) AS verdict,
 round(bad_mean, 9) AS bad_mean, round(bad_low, 9) AS bad_low FROM seen LEFT JOIN known USING (host)"""
