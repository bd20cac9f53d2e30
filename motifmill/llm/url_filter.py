"""URL filtering by listed rules and by mined association rules; DataFrame functions only.

Listed rules (host/path, allow or block) judge the pages they fit; the longest fit wins.
Spark's FP-growth then mines combinations of URL tokens from labelled pages, so that pages
that no listed rule fits are judged as well.  A label is given (page_id, blocked), or else it
is the verdict of the listed rule that fits the page; pages without a label teach nothing.
Labelled pages whose crc32(page_id as text) mod 5 is 0 are held out of the mining, and
measured() tells the precision and recall that the mined rules alone have on them.

A rule is kept if its support is MIN_SUPPORT and LEAST_PAGES pages or more, its confidence
MIN_CONFIDENCE or more, and no rule of the same verdict on a part of its tokens is as
strong, strength being the lower bound of the confidence (Wilson, at 1.64 deviations).
Rules are laid out as an inverted index from token to rules; a page's tokens look up their
rules and a rule fires when all its tokens are present.  The page gets the verdict of the
strongest fired rule (block wins ties; allow where none fires).

Mining reads at most MOST_LABELLED labelled pages, chosen by hash (a bound on the fit), and
rules have MOST_TOKENS tokens at most (the form of a rule);
every page is judged by all of its tokens.  Narrow apart from the mining: no shuffle of pages.

Special cases: a null url, or one without ://, has an empty host and path and is allowed
by default; rows are judged each by itself, so repeats and ties repeat; labels of one page
that differ count as blocked; no rows give
none; extra columns are ignored.
"""

from __future__ import annotations

from itertools import combinations

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import base

# The listed rules.
LISTED = (
    ("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"),
    ("net", "/es/", "block"), ("net", "/fr/", "block"),
)
MIN_SUPPORT, LEAST_PAGES, MIN_CONFIDENCE, MOST_TOKENS, MOST_LABELLED = 0.002, 3, 0.8, 4, 200_000
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit("")), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def listed_rule(host: Column, path: Column, rules=LISTED) -> tuple[Column, Column]:
    """(rule text, verdict) of the longest rule that fits; nulls where none does."""
    fits = [
        ((((host == h) | host.endswith("." + h)) & path.startswith(p)), h + p, verdict)
        for h, p, verdict in sorted(rules, key=lambda r: (-len(r[0] + r[1]), r[0]))
    ]
    null = F.lit(None).cast("string")
    text, verdict = null, null
    for fit, rule, v in reversed(fits):
        text, verdict = F.when(fit, F.lit(rule)).otherwise(text), F.when(fit, F.lit(v)).otherwise(verdict)
    return text, verdict


def url_tokens(url: Column, host: Column, path: Column) -> Column:
    """Distinct tokens: scheme, domain parts, and all words of the host, path steps and query keys."""
    labels = F.split(host, r"\.")
    tag = lambda name, values: F.transform(values, lambda v: F.concat(F.lit(name + "="), v))
    short = lambda v: F.regexp_replace(v, "[0-9]+", "#")
    query = F.regexp_extract(F.coalesce(url, F.lit("")), r"\?([^#]*)", 1)
    steps = F.split(short(path), "/")
    parts = F.concat(
        tag("scheme", F.array(F.regexp_extract(F.coalesce(url, F.lit("")), r"^([A-Za-z]+)://", 1))),
        tag("tld", F.array(F.element_at(labels, -1))),
        tag("domain", F.array(F.array_join(F.slice(labels, F.greatest(F.size(labels) - 1, F.lit(1)), 2), "."))),
        tag("word", F.split(host, r"[.\-]")),
        tag("step", F.slice(steps, 2, F.size(steps))),
        tag("ext", F.array(F.regexp_extract(path, r"\.([A-Za-z0-9]+)$", 1))),
        tag("key", F.transform(F.split(query, "&"), lambda v: F.split(v, "=")[0])),
    )
    return F.array_sort(F.array_distinct(F.filter(parts, lambda v: ~v.endswith("="))))


def judged(pages: DataFrame, rules=LISTED) -> DataFrame:
    host, path = host_of(F.col("url")), path_of(F.col("url"))
    df = pages.select(F.col("page_id").cast("long").alias("page_id"), "url").withColumns({"host": host, "path": path})
    text, verdict = listed_rule(F.col("host"), F.col("path"), rules)
    return df.withColumns({"rule": text, "listed": verdict, "tokens": url_tokens(F.col("url"), F.col("host"), F.col("path"))})


def labelled(pages: DataFrame, labels: DataFrame | None = None, rules=LISTED) -> DataFrame:
    """judged(pages) with a label (block or allow) and held_out; pages without a label are left out."""
    df = judged(pages, rules).withColumn("held_out", F.coalesce(F.crc32(F.col("page_id").cast("string").cast("binary")) % 5 == 0, F.lit(False)))
    if labels is None:
        return df.where("listed is not null").withColumn("label", F.col("listed"))
    known = labels.where("page_id is not null and blocked is not null").groupBy(F.col("page_id").cast("long").alias("page_id")).agg(F.max(F.col("blocked").cast("int")).alias("b"))
    return df.join(known, "page_id").withColumn("label", F.when(F.col("b") == 1, "block").otherwise("allow")).drop("b")


Rule = tuple[tuple[str, ...], str, float]


def mine_rules(pages: DataFrame, labels: DataFrame | None = None, rules=LISTED, min_support=MIN_SUPPORT, min_confidence=MIN_CONFIDENCE) -> list[Rule]:
    """(tokens, verdict, strength) of the rules that the labelled pages, without those held out, teach."""
    df = labelled(pages, labels, rules).where("not held_out")
    total = df.count()
    if not total:
        return []
    if total > MOST_LABELLED:
        df = df.where(F.pmod(F.xxhash64("page_id"), F.lit(1_000_000)) < int(1_000_000 * MOST_LABELLED / total))
    taught = min(total, MOST_LABELLED)
    items = df.select(F.array_append("tokens", F.concat(F.lit("label="), "label")).alias("items"))
    model = FPGrowth(itemsCol="items", minSupport=max(min_support, LEAST_PAGES / taught), minConfidence=min_confidence).fit(items)
    p, n, z = F.col("confidence"), F.col("support") * taught / F.col("confidence"), 1.64
    strength = (p + z * z / (2 * n) - z * F.sqrt(p * (1 - p) / n + z * z / (4 * n * n))) / (1 + z * z / n)
    found = model.associationRules.where(
        F.col("consequent")[0].isin("label=block", "label=allow") & (F.size("antecedent") <= MOST_TOKENS)
    ).select(F.array_sort("antecedent").alias("tokens"), F.substring(F.col("consequent")[0], 7, 5).alias("verdict"), strength.alias("strength"))
    # as many as the support lets through: a page's token sets, over MIN_SUPPORT
    kept: dict[tuple[frozenset, str], float] = {}
    for row in found.orderBy(F.size("tokens"), "tokens").collect():
        own = [t for size in range(1, len(row.tokens)) for t in combinations(row.tokens, size)]
        if all(kept.get((frozenset(t), row.verdict), -1.0) < row.strength for t in own):
            kept[frozenset(row.tokens), row.verdict] = row.strength
    return sorted(((tuple(sorted(t)), v, s) for (t, v), s in kept.items()), key=lambda r: (-r[2], len(r[0]), r[0], r[1]))


def measured(pages: DataFrame, labels: DataFrame | None = None, rules=LISTED) -> DataFrame:
    """verdict, pages, precision, recall of the mined rules alone on the held-out labelled pages."""
    mined = mine_rules(pages, labels, rules)
    held = labelled(pages, labels, rules).where("held_out").select("label", apply_rules(F.col("tokens"), mined).alias("said"))
    out = None
    for v in ("allow", "block"):
        both = F.count_if((F.col("label") == v) & (F.col("said") == v))
        part = held.agg(F.lit(v).alias("verdict"), F.count_if(F.col("label") == v).alias("pages"), F.try_divide(both, F.count_if(F.col("said") == v)).alias("precision"), F.try_divide(both, F.count_if(F.col("label") == v)).alias("recall"))
        out = part if out is None else out.unionByName(part)
    return out


def apply_rules(tokens: Column, mined: list[Rule]) -> Column:
    """Verdict of the strongest fired rule, by an inverted index of literals."""
    if not mined:
        return F.lit("allow")
    index: dict[str, list[int]] = {}
    for k, (own, _, _) in enumerate(mined):
        for t in own:
            index.setdefault(t, []).append(k)
    posting = F.create_map(*[x for t, ks in sorted(index.items()) for x in (F.lit(t), F.array(*map(F.lit, ks)))])
    needs = F.array(*[F.lit(len(own)) for own, _, _ in mined])
    order = sorted(range(len(mined)), key=lambda k: (-mined[k][2], mined[k][1] != "block", k))
    place = {k: i for i, k in enumerate(order)}
    rank = F.array(*[F.lit(place[k]) for k in range(len(mined))])
    verdicts = F.array(*[F.lit(mined[k][1]) for k in order])
    none = F.array().cast("array<int>")
    seen = F.flatten(F.transform(tokens, lambda t: F.coalesce(F.element_at(posting, t), none)))
    fired = F.filter(F.array_distinct(seen), lambda k: F.size(F.filter(seen, lambda x: x == k)) == F.element_at(needs, k + 1))
    first = F.array_min(F.transform(fired, lambda k: F.element_at(rank, k + 1)))
    return F.coalesce(F.element_at(verdicts, first + 1), F.lit("allow"))


def filter_urls(pages: DataFrame, labels: DataFrame | None = None, rules=LISTED) -> DataFrame:
    """page_id, host, path, rule, verdict and by (listed or mined)."""
    mined = mine_rules(pages, labels, rules)
    df = judged(pages, rules)
    return df.select(
        "page_id", "host", "path", "rule", F.coalesce("listed", apply_rules(F.col("tokens"), mined)).alias("verdict"),
        F.when(F.col("listed").isNotNull(), "listed").otherwise("mined").alias("decided_by"),
    )


def op4_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return filter_urls(base.table(spark, sf_dir, "pages", "page_id", "url"))
