"""URL filters: rules, then empirical-Bayes host reputation.

Page outcomes (1 bad, 0 good) are counted by host, registered domain and suffix. A beta-
binomial prior shrinks each suffix to the overall rate, each domain to its suffix and each
host to its domain; the priors' strengths are estimated by moments from the counts one
level below. A host is blocked if its bad share exceeds ``FACTOR`` times the overall share
(``THRESHOLD`` where that is less) with a posterior probability of at least 1 - ``RISK``:
the beta posterior's tail is evaluated by its continued fraction, so the bound is the exact
quantile's. Explicit rules go first.

DataFrame functions only. Counts are combined before the shuffle. Hosts of more than
1/``HEAVY`` of all pages are at most ``HEAVY`` and are broadcast; the others are joined by
a shuffle, in which the pages of heavy hosts are spread by page. Up to ``LITERAL_RULES``
rules are literals; more are joined to the distinct hosts by every suffix of a host.

Defined cases: a null url or one without ``://`` has empty host and path, counted as the
host ``''``; equal longest rules cannot be (rules are distinct); a page without an
outcome counts in no host; hosts without outcomes get their domain's, suffix's or the
overall posterior; no outcomes at all: everything is allowed; repeated pages count and
are judged each; other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import unused, written

THRESHOLD = 0.5
FACTOR = 1.5
RISK = 0.05
HEAVY = 1000
LITERAL_RULES = 500
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
# Second-level names under which registrations are made, in country domains.
SECOND_LEVEL = ("ac", "co", "com", "edu", "gov", "net", "org")
# Words of host or path that mark a page as bad.
URL_WORDS = ("ads", "adult", "bet", "bets", "betting", "casino", "escort", "gambling", "pills", "poker", "porn", "spam", "tracker", "viagra", "warez", "xxx")


def host_of(url: Column) -> Column:
    rest = F.substring(url, F.instr(url, "://") + 3, F.length(url))
    return F.when(F.instr(url, "://") > 0, F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), _UPPER, _LOWER)).otherwise(F.lit(""))


def path_of(url: Column) -> Column:
    rest = F.substring(url, F.instr(url, "://") + 3, F.length(url))
    return F.when(F.instr(url, "://") > 0, F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)).otherwise(F.lit(""))


def suffix_of(host: Column) -> Column:
    """The last label, or the last two of a country domain with a customary second level."""
    second = "|".join(SECOND_LEVEL)
    return F.regexp_extract(F.regexp_replace(host, r":\d*$", ""), rf"((?:(?:^|(?<=\.))(?:{second})\.[a-z]{{2}}|[^.]*))$", 1)


def domain_of(host: Column) -> Column:
    """The suffix and one label before it."""
    bare, suffix = F.regexp_replace(host, r":\d*$", ""), suffix_of(host)
    head = F.substring(bare, F.lit(1), F.length(bare) - F.length(suffix) - 1)
    label = F.element_at(F.split(head, r"\."), -1)
    return F.when(F.length(bare) <= F.length(suffix), bare).otherwise(F.concat(label, F.lit("."), suffix))


def rule_of(host: Column, path: Column, rules: list[tuple[str, str]]) -> Column:
    """The longest rule that fits, as a struct (rule, verdict); null without one. Rules are (verdict, 'host/path')."""
    out = None
    for verdict, rule in sorted(rules, key=lambda r: -len(r[1])):
        h, _, p = rule.partition("/")
        fits = ((host == h) | host.endswith("." + h)) & path.startswith("/" + p)
        hit = F.struct(F.lit(rule).alias("rule"), F.lit(verdict).alias("verdict"))
        out = F.when(fits, hit) if out is None else out.when(fits, hit)
    return out if out is not None else F.lit(None).cast("struct<rule:string,verdict:string>")


def rules_by_host(hosts: DataFrame, rules: DataFrame) -> DataFrame:
    """host, rules: for each distinct host the rules (verdict, rule) of the host or a domain above it, the longest first."""
    labels = F.split("host", r"\.")
    above = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    each = hosts.select("host", F.explode(above).alias("k"))
    named = rules.select(F.substring_index("rule", "/", 1).alias("k"), (-F.length("rule")).alias("order"), F.expr("substr(rule, instr(rule, '/'))").alias("path"), "rule", "verdict")
    return each.join(named, "k").groupBy("host").agg(F.sort_array(F.collect_list(F.struct("order", "path", "rule", "verdict"))).alias("rules"))


def page_outcomes(url: Column, html: Column) -> Column:
    """A label from the page itself: 1 if a word of its host or path is listed, or over a fifth of the words of its text end in a run of symbols; 0 if not; null if there is neither."""
    named = F.arrays_overlap(F.split(F.concat(host_of(url), path_of(url)), "[^a-z]+"), F.array(*map(F.lit, URL_WORDS)))
    body = F.regexp_replace(F.regexp_replace(F.regexp_replace(html, "(?s)<script[^A-Za-z].*?</script>", " "), "(?s)<style[^A-Za-z].*?</style>", " "), "<[^>]*>", " ")
    words = F.filter(F.split(F.coalesce(body, F.lit("")), r"[ \t\n\x0B\f\r]+", -1), lambda w: w != "")
    bad = F.size(F.filter(words, lambda w: w.rlike(r"[!#$%&*|]{2,}$|^\|$")))
    of_text = F.transform(F.array(words), lambda w: F.when(F.size(w) > 0, (5 * bad > F.size(w)).cast("int")))[0]
    return F.when(F.coalesce(named, F.lit(False)), F.lit(1)).otherwise(of_text)


# -- posterior ---------------------------------------------------------------------------


def log_gamma(x: Column) -> Column:
    """Stirling's series after eight steps up; to about 1e-13."""
    z = x + 8
    rest = F.lit(0.0)
    for i in range(8):
        rest = rest + F.log(x + i)
    return (z - 0.5) * F.log(z) - z + F.lit(0.9189385332046727) + 1 / (12 * z) - 1 / (360 * z * z * z) + 1 / (1260 * z * z * z * z * z) - rest


def beta_tail(x: float, a: Column, b: Column) -> Column:
    """P(share <= x) for a beta(a, b) share: the continued fraction, folded from its end. It takes some sqrt(a + b) terms."""
    turn = F.lit(x) > (a + 1) / (a + b + 2)
    p, q, y = F.when(turn, b).otherwise(a), F.when(turn, a).otherwise(b), F.when(turn, F.lit(1 - x)).otherwise(F.lit(x))

    def step(s: Column, m: Column) -> Column:
        h, p, q, y = F.floor(m / 2), s["p"], s["q"], s["y"]
        even = h * (q - h) * y / ((p + 2 * h - 1) * (p + 2 * h))
        odd = -(p + h) * (p + q + h) * y / ((p + 2 * h) * (p + 2 * h + 1))
        return s.withField("f", 1 + F.when(m % 2 == 0, even).otherwise(odd) / s["f"])

    def value(s: Column) -> Column:
        p, q, y = s["p"], s["q"], s["y"]
        front = F.exp(log_gamma(p + q) - log_gamma(p) - log_gamma(q) + p * F.log(y) + q * F.log(1 - y)) / p
        return front / F.aggregate(F.reverse(F.sequence(F.lit(1), (40 + 4 * F.sqrt(p + q)).cast("int"))), s, step, lambda t: t["f"])

    if x <= 0 or x >= 1:
        return F.lit(float(x >= 1))
    # the parameters are bound once by a lambda: written out, they would be repeated in every term
    bound = F.array(F.struct(F.lit(1.0).alias("f"), p.cast("double").alias("p"), q.cast("double").alias("q"), y.alias("y"), turn.alias("turn")))
    return F.transform(F.transform(bound, lambda s: F.struct(value(s).alias("v"), s["turn"].alias("turn"))), lambda t: F.when(t["turn"], 1 - t["v"]).otherwise(t["v"]))[0]


def strength(counts: DataFrame, parent: str) -> float:
    """The prior's strength (pseudo-pages) by moments: how far the shares of groups of one parent spread beyond what chance gives. One row reaches the driver."""
    counts = counts.filter(F.col("n") > 0)
    total = counts.groupBy(parent).agg(F.sum("n").alias("pn"), F.sum("bad").alias("pb"), F.sum(F.col("n") * F.col("n")).alias("n2"), F.sum(F.col("bad") * F.col("bad") / F.col("n")).alias("b2"), F.count(F.lit(1)).alias("k"))
    p = F.col("pb") / F.col("pn")
    within = F.col("b2") - F.col("pb") * p  # sum of n_i (p_i - p)^2
    row = total.filter((F.col("k") > 1) & (p > 0) & (p < 1)).agg(F.sum(within / (p * (1 - p)) - (F.col("k") - 1)).alias("a"), F.sum(F.col("pn") - F.col("n2") / F.col("pn") - (F.col("k") - 1)).alias("b")).first()
    if not row or row.a is None or not row.b or row.b <= 0:
        return 10.0
    rho = min(max(row.a / row.b, 1e-3), 0.95)
    return (1 - rho) / rho


def reputation(outcomes: DataFrame, hosts: DataFrame | None = None, threshold: float = THRESHOLD, factor: float = FACTOR, risk: float = RISK) -> DataFrame:
    """host, share (posterior mean), tail (posterior probability that the share is within the limit), blocked. outcomes: host, bad, n; hosts: further hosts (column host) without outcomes."""
    one = outcomes.select("host", "n", "bad")
    if hosts is not None:
        one = one.unionByName(hosts.select("host", F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("bad")))
    host = written(one.groupBy("host").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad")).withColumn("domain", domain_of(F.col("host"))).withColumn("suffix", suffix_of(F.col("host"))), "host-counts")
    domains = host.groupBy("domain", "suffix").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad"))
    suffixes = domains.groupBy("suffix").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad")).withColumn("all", F.lit(1))
    row = host.agg(F.sum("n").alias("n"), F.sum("bad").alias("bad")).first()
    if not row.n:
        return host.select("host", F.lit(0.0).alias("share"), F.lit(1.0).alias("tail"), F.lit(False).alias("blocked"))
    overall = row.bad / row.n
    limit = min(threshold, factor * overall)
    k = {"host": strength(host, "domain"), "domain": strength(domains, "suffix"), "suffix": strength(suffixes, "all")}
    post = lambda prior, s: (F.col("bad") + prior * s) / (F.col("n") + s)
    s = suffixes.select("suffix", post(F.lit(overall), k["suffix"]).alias("sp"))
    d = domains.join(s, "suffix").select("domain", "suffix", post(F.col("sp"), k["domain"]).alias("dp"))
    h = host.join(d, ["domain", "suffix"]).select("host", "n", "bad", "dp", post(F.col("dp"), k["host"]).alias("share"))
    a, b = F.col("bad") + F.col("dp") * k["host"], F.col("n") - F.col("bad") + (1 - F.col("dp")) * k["host"]
    tail = F.when(F.col("dp") <= 0, F.lit(1.0)).when(F.col("dp") >= 1, F.lit(0.0)).otherwise(beta_tail(limit, a, b))
    return h.select("host", "share", tail.alias("tail")).withColumn("blocked", F.col("tail") < risk)


def judge(pages: DataFrame, outcomes: DataFrame, rules: list[tuple[str, str]], *, id_col: str = "page_id", url_col: str = "url", threshold: float = THRESHOLD, factor: float = FACTOR, risk: float = RISK, literal_rules: int = LITERAL_RULES) -> DataFrame:
    """page_id, host, path, rule, verdict, share and tail (of the host). outcomes: host, bad, n (counts of labelled pages)."""
    src = pages.select(F.col(id_col).alias("page_id"), host_of(F.col(url_col)).alias("host"), path_of(F.col(url_col)).alias("path"))
    sizes = written(src.groupBy("host").agg(F.count(F.lit(1)).alias("n_pages")), "host-pages")
    known = reputation(outcomes, sizes, threshold, factor, risk).join(sizes, "host").withColumn("rules", F.lit(None).cast("array<struct<order:int,path:string,rule:string,verdict:string>>"))
    if len(rules) > literal_rules:
        spark = pages.sparkSession
        found = rules_by_host(sizes, spark.createDataFrame([(r, v) for v, r in rules], "rule string, verdict string"))
        known = known.drop("rules").join(found, "host", "left")
    known = written(known, "host-reputation")
    total = known.agg(F.sum("n_pages")).first()[0] or 0
    facts = F.struct("share", "tail", "blocked", "rules")
    heavy = F.col("n_pages") * HEAVY > total  # fewer than HEAVY hosts, whatever the data
    (name,) = unused(src, "found")
    first = src.join(F.broadcast(known.filter(heavy).select("host", facts.alias(name))), "host", "left")
    light = known.filter(~heavy).select(F.col("host").alias("k"), facts.alias("r"))
    key = F.when(F.col(name).isNull(), F.col("host")).otherwise(F.concat(F.lit("\x00"), F.coalesce(F.col("page_id").cast("string"), F.lit(""))))
    both = first.withColumn("key", key).join(light, F.col("key") == F.col("k"), "left").withColumn("got", F.coalesce(name, "r"))
    if len(rules) > literal_rules:
        fits = F.filter("got.rules", lambda r: F.col("path").startswith(r["path"]))
        rule = F.when(F.size(fits) > 0, F.struct(fits[0]["rule"].alias("rule"), fits[0]["verdict"].alias("verdict")))
    else:
        rule = rule_of(F.col("host"), F.col("path"), rules)
    own = F.when(F.col("got.blocked"), "block").otherwise("allow")
    return both.withColumn("hit", rule).select("page_id", "host", "path", F.col("hit.rule").alias("rule"), F.coalesce("hit.verdict", own).alias("verdict"), F.col("got.share").alias("share"), F.col("got.tail").alias("tail"))


def count_outcomes(pages: DataFrame, *, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """host, bad, n from the label that each page itself gives."""
    bad = page_outcomes(F.col(url_col), F.col(html_col))
    return pages.select(host_of(F.col(url_col)).alias("host"), bad.alias("bad")).filter(F.col("bad").isNotNull()).groupBy("host").agg(F.count(F.lit(1)).alias("n"), F.sum("bad").alias("bad"))


def sql(rules: list[tuple[str, str]], threshold: float = THRESHOLD, factor: float = FACTOR, risk: float = RISK) -> str:
    """The same judgement in DuckDB; share and tail to six decimals."""
    words = ", ".join(f"'{w}'" for w in URL_WORDS)
    rows = ", ".join(f"('{v}', '{r}')" for v, r in rules)
    second = "|".join(SECOND_LEVEL)
    moments = lambda src, parent: (
        f"(SELECT CASE WHEN sum(b) IS NULL OR sum(b) <= 0 THEN 10.0::DOUBLE ELSE (1 - least(greatest(sum(a) / sum(b), 1e-3), 0.95)) / least(greatest(sum(a) / sum(b), 1e-3), 0.95) END FROM ("
        f"SELECT (sum(bad * bad / n::DOUBLE) - sum(bad) * (sum(bad) / sum(n))) / ((sum(bad) / sum(n)) * (1 - sum(bad) / sum(n))) - (count(n) - 1) AS a, sum(n) - sum(n * n) / sum(n) - (count(n) - 1) AS b "
        f"FROM (SELECT {parent} AS parent, nullif(n, 0) AS n, bad::DOUBLE AS bad FROM {src}) GROUP BY parent HAVING count(n) > 1 AND sum(bad) > 0 AND sum(bad) < sum(n)))"
    )
    return rf"""
WITH u AS (SELECT page_id, coalesce(translate(regexp_extract(CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) END, '^([^/?#]*)', 1), '{_UPPER}', '{_LOWER}'), '') AS host,
  coalesce(regexp_extract(CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) END, '^[^/?#]*([^?#]*)', 1), '') AS path,
  list_filter(regexp_split_to_array(regexp_replace(regexp_replace(regexp_replace(coalesce(html, ''), '<script[^A-Za-z].*?</script>', ' ', 'gs'), '<style[^A-Za-z].*?</style>', ' ', 'gs'), '<[^>]*>', ' ', 'g'), '[ \t\n\x0B\f\r]+'), lambda w: w <> '') AS w FROM pages
), o AS (SELECT host, CASE WHEN list_has_any(regexp_split_to_array(host || path, '[^a-z]+'), [{words}]) THEN 1 WHEN len(w) > 0 THEN (5 * len(list_filter(w, lambda x: regexp_matches(x, '[!#$%&*|]{{2,}}$|^\|$'))) > len(w))::INT END AS bad FROM u
), h0 AS (SELECT host, count(bad) AS n, coalesce(sum(bad), 0) AS bad, regexp_replace(host, ':[0-9]*$', '') AS bare FROM o GROUP BY host
), h1 AS (SELECT *, CASE WHEN regexp_matches(bare, '(^|\.)({second})\.[a-z]{{2}}$') THEN regexp_extract(bare, '(({second})\.[a-z]{{2}})$', 1) ELSE regexp_extract(bare, '([^.]*)$', 1) END AS suffix FROM h0
), h AS (SELECT host, n, bad, suffix, CASE WHEN length(bare) <= length(suffix) THEN bare ELSE string_split(substr(bare, 1, length(bare) - length(suffix) - 1), '.')[-1] || '.' || suffix END AS domain FROM h1
), d AS (SELECT domain, suffix, sum(n) AS n, sum(bad) AS bad FROM h GROUP BY domain, suffix
), s AS (SELECT suffix, sum(n) AS n, sum(bad) AS bad FROM d GROUP BY suffix
), t AS (SELECT sum(n) AS n, sum(bad) / sum(n) AS p, least({threshold}::DOUBLE, {factor}::DOUBLE * sum(bad) / sum(n)) AS x FROM h
), k AS (SELECT {moments('h', 'domain')} AS kh, {moments('d', 'suffix')} AS kd, {moments('s', '1')} AS ks
), hp AS (SELECT h.host, h.n, h.bad, kh, x, (d.bad + kd * (s.bad + ks * p) / (s.n + ks)) / (d.n + kd) AS dp FROM h JOIN d ON h.domain = d.domain AND h.suffix = d.suffix JOIN s ON h.suffix = s.suffix, t, k
), ab AS (SELECT host, dp, (bad + dp * kh) / (n + kh) AS share, x, bad + dp * kh AS a, n - bad + (1 - dp) * kh AS b FROM hp
), v AS (SELECT *, x > (a + 1) / (a + b + 2) AS turn FROM ab
), pq AS (SELECT *, CASE WHEN turn THEN b ELSE a END AS p, CASE WHEN turn THEN a ELSE b END AS q, CASE WHEN turn THEN 1 - x ELSE x END AS y FROM v
), cf AS (SELECT host, share, dp, x, turn, exp(lgamma(p + q) - lgamma(p) - lgamma(q) + p * ln(y) + q * ln(1 - y)) / p / list_reduce(list_concat([1.0::DOUBLE], list_reverse(range(1, (40 + 4 * sqrt(p + q))::INT + 2))::DOUBLE[]),
    lambda f, m: 1 + CASE WHEN m % 2 = 0 THEN (m / 2) * (q - m / 2) * y / ((p + m - 1) * (p + m)) ELSE -(p + floor(m / 2)) * (p + q + floor(m / 2)) * y / ((p + 2 * floor(m / 2)) * (p + 2 * floor(m / 2) + 1)) END / f) AS part FROM pq WHERE dp > 0 AND dp < 1
), rep AS (SELECT ab.host, ab.share, CASE WHEN ab.dp <= 0 OR ab.x >= 1 THEN 1.0 WHEN ab.dp >= 1 OR ab.x <= 0 THEN 0.0 WHEN turn THEN 1 - part ELSE part END AS tail FROM ab LEFT JOIN cf ON ab.host = cf.host
), rules AS (SELECT verdict, rule, split_part(rule, '/', 1) AS rh, substr(rule, instr(rule, '/')) AS rp FROM (VALUES {rows}) v(verdict, rule)
), hit AS (SELECT page_id, arg_max(rule, length(rule)) AS rule, arg_max(verdict, length(rule)) AS verdict FROM u JOIN rules ON (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp) GROUP BY page_id)
SELECT u.page_id, u.host, u.path, hit.rule, coalesce(hit.verdict, CASE WHEN t.n > 0 AND tail < {risk} THEN 'block' ELSE 'allow' END) AS verdict,
  floor(CASE WHEN t.n > 0 THEN share ELSE 0.0 END * 1e6 + 0.5) / 1e6 AS share, floor(CASE WHEN t.n > 0 THEN tail ELSE 1.0 END * 1e6 + 0.5) / 1e6 AS tail
FROM u JOIN rep ON u.host = rep.host LEFT JOIN hit ON u.page_id = hit.page_id, t
"""
