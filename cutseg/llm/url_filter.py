"""URL verdicts: host and path rules, and for all other URLs a logistic
regression on hashed character trigrams of host and path.

The model is fitted on the small table below, on the driver.  Scoring is SQL
expressions only; weights are whole millionths, so sums are exact in any order.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
from pyspark.sql import Column, DataFrame, functions as F

BUCKETS = 1024
#: Hash constants of a trigram: code points at 1, 31 and 961; a path's trigrams are shifted.
STEP, PATH_SHIFT = 31, 517

#: Hosts without their last label, and paths: to allow, and to block.
ALLOWED = [
    ("news.example-daily", "/world/2024/05/harvest-report"), ("blog.gardeners", "/spring/planting-guide"),
    ("docs.library-project", "/manual/chapter-2.html"), ("www.museum-city", "/exhibits/bronze-age"),
    ("school.riverside", "/courses/algebra/lesson-4"), ("wiki.openatlas", "/article/mountain-passes"),
    ("recipes.homecook", "/soups/lentil.html"), ("journal.oceanlab", "/papers/tides-and-currents"),
    ("forum.woodworkers", "/thread/12345-oak-joinery"), ("www.weatherarchive", "/stations/north/1998"),
    ("history.townrecords", "/letters/1871/index.html"), ("science.readers", "/questions/why-sky-blue"),
    ("podcast.linguistics", "/episodes/vowel-harmony"), ("help.sparse-tools", "/install/linux"),
    ("m.travelnotes", "/fr/alpes/randonnee"), ("www.poemsonline", "/de/gedichte/herbst"),
    ("magazine.astronomy", "/es/planetas/saturno"), ("data.cityplan", "/en/reports/water-supply"),
    ("blog.teacherdesk", "/en/reading-list"), ("www.birdwatch", "/en/species/heron"),
    ("m.cooking.example", "/en/123"), ("www.hiking-club", "/de/touren/alpen"),
    ("garden-center", "/fr/roses"), ("library.north", "/es/libros/historia"),
    ("city-news.example", "/en/456"), ("blog.carpentry", "/oak/table.html"),
]
BLOCKED = [
    ("win-casino-bonus", "/free-spins/claim-now"), ("cheap-pills-online", "/buy/viagra-discount"),
    ("adult-xxx-cams", "/live/hot-girls"), ("click-ads-tracker", "/track?aff=1"),
    ("free-crypto-giveaway", "/double-your-coins"), ("payday-loan-fast", "/apply/instant-cash"),
    ("download-warez-crack", "/keygen/full-version"), ("poker-bets-vip", "/jackpot/register"),
    ("hot-singles-chat", "/adult/join-free"), ("replica-watches-sale", "/cheap/rolex"),
    ("spam-mailer-lists", "/buy/leads"), ("xxx-tube-videos", "/porn/free"),
    ("weightloss-miracle", "/pills/order-now"), ("casino-slots-win", "/bonus/no-deposit"),
    ("login-verify-account", "/secure/update-password"), ("prize-winner-alert", "/claim/gift-card"),
    ("torrent-cracks", "/warez/serials"), ("bet-odds-vip", "/free-bets/claim"),
    ("seo-backlinks-cheap", "/buy/links"), ("ads.popunder-net", "/click/redirect"),
    ("m.casino-win.example", "/en/123"), ("free-bets.example", "/de/wetten"),
    ("xxx-cams-live", "/fr/adult"), ("www.cheap-pills", "/es/viagra"),
]
#: Last labels, dealt in turn to hosts of both kinds, so that none tells the kind.
LAST_LABELS = ("net", "biz", "info", "com", "org")
#: host, path, 1 = block or 0 = allow
LABELLED_URLS = [(f"{h}.{LAST_LABELS[i % len(LAST_LABELS)]}", p, y) for y, urls in ((0, ALLOWED), (1, BLOCKED)) for i, (h, p) in enumerate(urls)]

#: (host, path, verdict); a rule fits its host, all subdomains, and paths that start with its path.
RULES = [("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block")]


def _buckets(text: str, shift: int) -> list[int]:
    codes = [ord(c) for c in f"^{text}$"]
    return [(a * STEP * STEP + b * STEP + c + shift) % BUCKETS for a, b, c in zip(codes, codes[1:], codes[2:])]


def features(host: str, path: str) -> np.ndarray:
    """Counts of hashed trigrams of host and path, with marks at both ends."""
    return np.bincount(_buckets(host, 0) + _buckets(path, PATH_SHIFT), minlength=BUCKETS).astype(float)


@lru_cache(1)
def fitted(rounds: int = 400, rate: float = 0.05, ridge: float = 0.01) -> tuple[tuple[int, ...], int]:
    """Weights and bias in millionths, by gradient descent on the table."""
    x = np.array([features(h, p) for h, p, _ in LABELLED_URLS])
    y = np.array([label for *_, label in LABELLED_URLS], float)
    w, bias = np.zeros(BUCKETS), 0.0
    for _ in range(rounds):
        miss = 1 / (1 + np.exp(-(x @ w + bias))) - y
        w -= rate * (x.T @ miss / len(y) * 10 + ridge * w)
        bias -= rate * miss.mean()
    return tuple(int(v) for v in np.rint(w * 1e6)), int(round(bias * 1e6))


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host up to ``/ ? #`` with A-Z lower-cased, and path up to ``? #``; both
    empty for a null url or one without ``://``."""
    at = F.locate("://", url)
    rest = F.when(at > 0, F.substr(url, at + 3)).otherwise(F.lit(""))
    host = F.translate(F.regexp_extract(rest, "^[^/?#]*", 0), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return F.coalesce(host, F.lit("")), F.coalesce(F.regexp_extract(rest, "^[^/?#]*([^?#]*)", 1), F.lit(""))


def _trigram_sum(text: Column, shift: int, weights: Column) -> Column:
    codes = F.transform(F.split(F.concat(F.lit("^"), text, F.lit("$")), ""), F.ascii)
    codes = F.filter(codes, lambda c: c > 0)
    n = F.greatest(F.size(codes) - 2, F.lit(0))
    # three shifted copies: linear in the text, the code points are not computed again for each place
    two = F.zip_with(F.slice(codes, 1, n), F.slice(codes, 2, n), lambda a, b: a * (STEP * STEP) + b * STEP + shift)
    hashes = F.zip_with(two, F.slice(codes, 3, n), lambda ab, c: (ab + c) % BUCKETS)
    return F.aggregate(hashes, F.lit(0).cast("long"), lambda acc, h: acc + F.element_at(weights, h.cast("int") + 1))


def judge(pages: DataFrame, rules=RULES, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """``page_id, host, path, rule, verdict, score``: one row per input row.

    ``score`` is the model's log-odds in millionths (over 0: block), for every
    url; the longest fitting rule overrides it.  Repeated rows are judged alike.
    """
    weights, bias = fitted()
    host, path = host_and_path(pages[url_col].cast("string"))
    rows = pages.select(pages[id_col].alias("page_id"), host.alias("host"), path.alias("path"))
    fits = lambda h, p: ((F.col("host") == h) | F.col("host").endswith("." + h)) & F.col("path").startswith(p)
    rule, ruled = F.lit(None).cast("string"), F.lit(None).cast("string")
    for h, p, verdict in sorted(rules, key=lambda r: len(r[0] + r[1])):
        rule = F.when(fits(h, p), F.lit(h + p)).otherwise(rule)
        ruled = F.when(fits(h, p), F.lit(verdict)).otherwise(ruled)
    table = F.array(*[F.lit(w) for w in weights]).cast("array<long>")
    score = _trigram_sum(F.col("host"), 0, table) + _trigram_sum(F.col("path"), PATH_SHIFT, table) + F.lit(bias)
    rows = rows.withColumns({"rule": rule, "ruled": ruled, "score": score.cast("long")})
    return rows.select("page_id", "host", "path", "rule", F.coalesce("ruled", F.when(F.col("score") > 0, "block").otherwise("allow")).alias("verdict"), "score")


def op10_url_filter(spark, sf_dir: str) -> DataFrame:
    return judge(spark.read.parquet(f"{sf_dir}/pages.parquet"))


def op10_sql() -> str:
    weights, bias = fitted()
    part = lambda col, shift: (
        f"coalesce(list_sum(list_transform(range(1, greatest(length({col}), 0) + 1), lambda i: w[((unicode(substr('^' || {col} || '$', i, 1)) * {STEP * STEP}"
        f" + unicode(substr('^' || {col} || '$', i + 1, 1)) * {STEP} + unicode(substr('^' || {col} || '$', i + 2, 1)) + {shift}) % {BUCKETS}) + 1])), 0)")
    fit = lambda h, p: f"(host = '{h}' or ends_with(host, '.{h}')) and starts_with(path, '{p}')"
    by_length = sorted(RULES, key=lambda r: -len(r[0] + r[1]))
    case = lambda pick: "case " + " ".join(f"when {fit(h, p)} then '{pick(h, p, v)}'" for h, p, v in by_length) + " end"
    return f"""
with rest as (select page_id, case when position('://' in url) > 0 then substr(url, position('://' in url) + 3) else '' end as r from pages),
parts as (select page_id, translate(regexp_extract(r, '^[^/?#]*', 0), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
  regexp_extract(r, '^[^/?#]*([^?#]*)', 1) as path from rest),
model as (select [{', '.join(map(str, weights))}] as w),
scored as (select page_id, host, path, ({part('host', 0)} + {part('path', PATH_SHIFT)} + ({bias}))::bigint as score from parts, model)
select page_id, host, path, {case(lambda h, p, v: h + p)} as rule,
  coalesce({case(lambda h, p, v: v)}, case when score > 0 then 'block' else 'allow' end) as verdict, score from scored"""
