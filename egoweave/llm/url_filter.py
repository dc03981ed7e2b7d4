"""Operator 3: URL rules, and logistic regression over hashed character trigrams for the rest.

Everything on the judged table is a DataFrame expression. The model is fitted on a small labelled table (url, label; 1 to
block), counted against LABEL_ROWS, on the driver, in an order fixed by the rows; its weights are whole numbers (millionths), so
sums do not depend on their order. No labelled URLs are given, so the query's table is made from the word lists below,
generic words of either kind in pairs; none of its hosts is a host that the tests or the query judge.

A url that is null or has no "://" has an empty host and path. A rule "host/path" fits its host and subdomains if
the path begins with the rule's; the longest fitting rule wins (equal lengths: the first in text order). Without a rule the
method decides; a logit of zero blocks. Repeated rows stay, null page_ids too; an empty table gives an empty result; other
columns are not read. Without labelled rows the weights are zero and the bias allows. Labelled rows with a null url or label are left out.
"""

from __future__ import annotations

import math
import re
import zlib
from functools import lru_cache

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

PLACES, SCALE = 4096, 1_000_000
RATE, DECAY, ROUNDS = 0.3, 1e-3, 40
LABEL_ROWS = 20_000

# fixed values: words of hosts that are to be blocked and of hosts that are not
BLOCKED_WORDS = "adult ads bets betting bonus cams casino cheap click crack escort farm free jackpot loan lotto meds nude payday pharma phish pills poker popup porn promo scam slots spam spins track viagra warez win xxx".split()
ALLOWED_WORDS = "archive art atlas author bakery bank biology bird book bridge cafe castle chess city clinic code concert county data dental desk doctor earth energy ether farmers film forest forum garden guitar harbor health history hotel house journal kitchen law leather letter library local maps math mother museum music nation nature network news north ocean open other parent partner photo physics radio reader recipe river school science shop station store street student summer theater there thing third this thought thread tower train travel union valley water weather whether wiki winter world writer".split()
TOPS = "com net org info".split()
LEADS = ["", "www.", "m.", "blog."]
PATHS = "/ /en/1 /de/20.html /fr/300/ /es/4 /en/55 /article/678.html /index.html /a/b".split()


def labelled() -> list[tuple[str, int]]:
    """(url, label) of words alone and in pairs, with tops, leads and paths in turn."""
    out, k = [], 0
    for label, words, steps in ((1, BLOCKED_WORDS, (1, 2, 3, 5, 8, 13)), (0, ALLOWED_WORDS, (1, 3, 7, 11, 19))):
        names = list(words)
        for step in steps:
            names += [f"{w}-{words[(i + step) % len(words)]}" for i, w in enumerate(words)]
        for name in names:
            out.append((f"https://{LEADS[k % len(LEADS)]}{name}.{TOPS[k % 7 % len(TOPS)]}{PATHS[k % len(PATHS)]}", label))
            k += 1
    return out


def places(host: str, path: str) -> list[int]:
    return [(ord(s[i]) * 7919 + ord(s[i + 1]) * 104729 + ord(s[i + 2]) * 1299709 + salt) % PLACES for s, salt in ((f"^{host}$", 0), (path, 577)) for i in range(len(s) - 2)]


def parts(url: str) -> tuple[str, str]:
    """As split_url, for the labelled rows."""
    _, found, rest = url.partition("://")
    raw = re.match(r"[^/?#]*", rest).group() if found else ""
    return raw.translate(LOWER), re.match(r"[^?#]*", rest[len(raw) :]).group() if found else ""


LOWER = {c: c + 32 for c in range(65, 91)}


def fit(rows: list[tuple[str, int]]) -> tuple[tuple[int, ...], int]:
    """Weights by place and the bias, in millionths."""
    w, bias = [0.0] * PLACES, -1.0
    known = [(places(*parts(u)), int(y)) for u, y in sorted({(u, y) for u, y in rows if u is not None and y is not None}, key=lambda r: (zlib.crc32(r[0].encode()), r))]
    for turn in range(ROUNDS):
        step = RATE / (1 + turn / 5)
        for at, y in known:
            g = 1 / (1 + math.exp(-max(-30.0, min(30.0, bias + sum(w[i] for i in at))))) - y
            bias -= 0.1 * step * g
            for i in at:
                w[i] -= step * (g + DECAY * w[i])
    return tuple(round(x * SCALE) for x in w), round(bias * SCALE)


def says(model: tuple[tuple[int, ...], int], url: str) -> str:
    """What the model alone says of a url."""
    return "block" if model[1] + sum(model[0][i] for i in places(*parts(url))) >= 0 else "allow"


def read_labels(labels: DataFrame) -> list[tuple[str, int]]:
    """The rows of a labelled table (url, label), which must be small."""
    rows = labels.select("url", "label").limit(LABEL_ROWS + 1).collect()  # a row more than allowed, to see that there are too many
    if len(rows) > LABEL_ROWS:
        raise ValueError(f"more than {LABEL_ROWS} labelled rows")
    return [(r.url, r.label) for r in rows]


@lru_cache
def own_model() -> tuple[tuple[int, ...], int]:
    return fit(labelled())


def split_url(url: Column) -> tuple[Column, Column]:
    """Host and path columns."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url)))
    raw = F.regexp_extract(rest, "^[^/?#]*", 0)
    path = F.regexp_extract(F.substring(rest, F.length(raw) + 1, F.length(rest)), "^[^?#]*", 0)
    host = F.translate(raw, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return F.coalesce(host, F.lit("")), F.coalesce(path, F.lit(""))


def logit(host: Column, path: Column, model: tuple[tuple[int, ...], int]) -> Column:
    """Bias plus the weights of all trigrams, in millionths."""
    table, bias = model
    w = F.expr("array(" + ",".join(f"{x}L" for x in table) + ")")

    def total(s: Column, salt: int) -> Column:
        code = lambda i: F.ascii(F.substring(s, i, F.lit(1))).cast("bigint")
        grams = F.aggregate(F.sequence(F.lit(1), F.length(s) - 2), F.lit(0).cast("bigint"), lambda acc, i: acc + F.get(w, ((code(i) * 7919 + code(i + 1) * 104729 + code(i + 2) * 1299709 + salt) % PLACES).cast("int")))
        return F.when(F.length(s) >= 3, grams).otherwise(F.lit(0).cast("bigint"))

    return total(F.concat(F.lit("^"), host, F.lit("$")), 0) + total(path, 577) + F.lit(bias).cast("bigint")


def rule_of(host: Column, path: Column, rules: dict[str, str]) -> tuple[Column, Column]:
    """The winning rule and its action, null where none fits."""
    rule, action = F.lit(None).cast("string"), F.lit(None).cast("string")
    for text in sorted(rules, key=lambda r: (len(r), [-ord(c) for c in r])):
        h, slash, p = text.partition("/")
        h = h.lower()
        fits = ((host == h) | F.endswith(host, F.lit("." + h))) & F.startswith(path, F.lit(slash + p))
        rule, action = F.when(fits, text).otherwise(rule), F.when(fits, rules[text]).otherwise(action)
    return rule, action


def judge(pages: DataFrame, rules: dict[str, str], labels: DataFrame | None = None) -> DataFrame:
    """(page_id, host, path, rule, verdict) of pages (page_id, url), by rules and a model of labels (url, label) or of the table above."""
    model = own_model() if labels is None else fit(read_labels(labels))
    host, path = split_url(F.col("url"))
    rows = pages.select("page_id", host.alias("host"), path.alias("path"))
    rule, action = rule_of(F.col("host"), F.col("path"), rules)
    said = F.when(logit(F.col("host"), F.col("path"), model) >= 0, "block").otherwise("allow")
    return rows.select("page_id", "host", "path", rule.alias("rule"), F.coalesce(action, said).alias("verdict"))


# fixed values: the rules of the query
RULES = {"com/en/": "block", "example.com/en/7": "allow", "net/de/": "allow", "example.net/de/8": "block", "org/es/": "block"}


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(spark.read.parquet(f"{sf_dir}/pages.parquet"), RULES)


def sql() -> str:
    """The query in DuckDB's SQL."""
    table, bias = own_model()
    gram = lambda s, salt: f"coalesce(list_sum(list_transform(range(1, length({s}) - 1), lambda i: w[1 + (unicode(substr({s}, i, 1)) * 7919 + unicode(substr({s}, i + 1, 1)) * 104729 + unicode(substr({s}, i + 2, 1)) * 1299709 + {salt}) % {PLACES}])), 0)"
    cases = sorted(RULES, key=lambda r: -len(r))
    fits = {r: f"(host = '{r.split('/')[0]}' or ends_with(host, '.{r.split('/')[0]}')) and starts_with(path, '{r[r.index('/'):]}')" for r in cases}
    rule = "case " + " ".join(f"when {fits[r]} then '{r}'" for r in cases) + " end"
    action = "case " + " ".join(f"when {fits[r]} then '{RULES[r]}'" for r in cases) + f" when {gram('framed', 0)} + {gram('path', 577)} + ({bias}) >= 0 then 'block' else 'allow' end"
    return f"""
with model as (select {list(table)}::bigint[] as w),
cut as (select page_id, case when instr(url, '://') > 0 then substr(url, instr(url, '://') + 3) else '' end as rest from pages),
part as (select page_id, rest, regexp_extract(rest, '^[^/?#]*') as raw from cut),
named as (select page_id, translate(raw, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
  regexp_extract(substr(rest, length(raw) + 1), '^[^?#]*') as path from part),
framed as (select *, '^' || host || '$' as framed from named)
select page_id, coalesce(host, '') as host, coalesce(path, '') as path, {rule} as rule, {action} as verdict
from framed, model"""
