"""URL filtering by association rules, in DataFrame and SQL functions only.

Fixed rules on host and path decide first. The rest is judged by combinations of URL tokens that FP-growth mines from
labelled pages: rules with enough support and confidence become an inverted index from token to rule, and a URL is
blocked when it holds every token of some rule.
"""

from __future__ import annotations

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ertransfer.durable import release, settle

#: Fixed values: (verdict, host, path start) of the rules that a query names.
DEFAULT_RULES = [("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/")]
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
BAD = "=block"


def _after_scheme(url: Column) -> Column:
    at = F.instr(url, "://")
    return F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))


def host_of(url: Column) -> Column:
    """The part after the first ``://`` up to ``/``, ``?``, ``#`` or the end, A-Z lower-cased; else empty."""
    return F.coalesce(F.translate(F.regexp_extract(_after_scheme(url), r"(?s)\A([^/?#]*)", 1), UPPER, LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    """What follows the host up to ``?``, ``#`` or the end; else empty."""
    return F.coalesce(F.regexp_extract(_after_scheme(url), r"(?s)\A[^/?#]*([^?#]*)", 1), F.lit(""))


def url_tokens(url: Column, host: Column, path: Column) -> Column:
    """Distinct tokens: the host's labels with their place from the right, path words with numbers folded, query keys."""
    labels = F.reverse(F.split(host, r"\."))
    hosts = F.transform(labels, lambda x, i: F.concat(F.lit("h"), i.cast("string"), F.lit(":"), x))
    words = F.filter(F.split(path, r"[/._-]+"), lambda x: x != "")
    words = F.transform(words, lambda x: F.concat(F.lit("p:"), F.regexp_replace(F.lower(x), r"[0-9]+", "0")))
    keys = F.transform(F.regexp_extract_all(F.coalesce(url, F.lit("")), F.lit(r"[?&]([^=&#]+)"), 1), lambda x: F.concat(F.lit("q:"), F.lower(x)))
    return F.array_distinct(F.when(host == "", F.array().cast("array<string>")).otherwise(F.concat(hosts, words, keys)))


def fixed_rule(host: Column, path: Column, rules=DEFAULT_RULES) -> tuple[Column, Column]:
    """(rule, verdict) of the longest rule that fits, both null if none fits."""
    rule = verdict = F.lit(None).cast("string")
    for kind, name, start in sorted(rules, key=lambda r: len(r[1] + r[2])):
        fits = ((host == name) | host.endswith("." + name)) & path.startswith(start)
        rule = F.when(fits, F.lit(name + start)).otherwise(rule)
        verdict = F.when(fits, F.lit(kind)).otherwise(verdict)
    return rule, verdict


def token_items(labelled: DataFrame, min_count: int) -> DataFrame:
    """Rows (token, item) of the tokens that at least ``min_count`` rows of ``labelled`` (at, tokens) hold.

    Tokens that the same rows hold are one item, the least of them: whatever rule one of them makes, each of them makes,
    so a page that holds any of them holds the item. No token is left out, and a long URL that repeats as a whole is
    one item and not as many combinations as its tokens have.
    """
    long = labelled.select("at", F.explode("tokens").alias("token"))
    mark = lambda seed: F.bit_xor(F.xxhash64(F.lit(seed), "at"))
    held = long.groupBy("token").agg(F.count("*").alias("n"), mark(1).alias("u"), mark(2).alias("v")).where(F.col("n") >= min_count)
    named = held.groupBy("n", "u", "v").agg(F.min("token").alias("item"))
    return held.join(named, ["n", "u", "v"]).select("token", "item")


def to_items(rows: DataFrame, items: DataFrame) -> DataFrame:
    """``rows`` (tokens, ...) with the items of their tokens as tokens; rows without any item are dropped."""
    rest = [c for c in rows.columns if c != "tokens"]
    met = rows.select(*rest, F.explode("tokens").alias("token")).join(items, "token")
    return met.groupBy(*rest).agg(F.array_sort(F.collect_set("item")).alias("tokens"))


def mine_rules(labelled: DataFrame, min_support: float = 0.002, min_confidence: float = 0.5, min_count: int = 5, min_lift: float = 1.5, min_z: float = 5.0) -> tuple[DataFrame, DataFrame] | None:
    """(rules, items) over ``labelled`` (tokens, bad boolean); None without labels.

    Rules are rows (rule long, tokens, confidence, support) whose tokens are items, see :func:`token_items`.

    A rule holds at least ``min_count`` labelled pages whatever their number, has the confidence, lifts the share of bad
    pages by ``min_lift`` and is ``min_z`` standard errors above it: among many combinations some look good by chance. All items of a URL are combined.
    """
    items = labelled.where("bad is not null and size(tokens) > 0")
    n, bad = items.agg(F.count("*"), F.coalesce(F.sum(F.col("bad").cast("int")), F.lit(0))).first()
    if not n:
        return None
    base = bad / n
    # A row's place names it, so the rows are written before any of them is told from another.
    keyed = settle(items.select(F.monotonically_increasing_id().alias("at"), "tokens", "bad"), "labelled")
    known = settle(token_items(keyed, min_count), "token-items")
    marked = to_items(keyed, known)
    found = settle(marked.select(F.when(F.col("bad"), F.concat("tokens", F.array(F.lit(BAD)))).otherwise(F.col("tokens")).alias("items")), "items")
    model = FPGrowth(itemsCol="items", minSupport=min(1.0, max(min_support, min_count / n)), minConfidence=min_confidence).fit(found)
    kept = found.count()  # pages without any item are not among them
    holding = F.col("support") * kept / F.col("confidence")  # labelled pages that hold the rule's tokens
    sure = (F.col("confidence") - base) * F.sqrt(holding) >= min_z * (base * (1 - base)) ** 0.5
    rules = model.associationRules.where(F.col("consequent") == F.array(F.lit(BAD))).where((F.col("confidence") >= min_lift * base) & sure)
    rules = settle(rules.select(F.xxhash64(F.array_sort("antecedent")).alias("rule"), F.col("antecedent").alias("tokens"), "confidence", (F.col("support") * kept / n).alias("support")), "rules")
    release(found, keyed)
    return rules, known


def matching_rules(token_sets: DataFrame, rules: DataFrame) -> DataFrame:
    """Rows (key, hits) for each of ``token_sets`` (key, tokens) that holds all tokens of a rule.

    A rule is posted under the rarest of its tokens alone, so a token that most URLs hold posts few rules or none.
    """
    often = token_sets.select(F.explode("tokens").alias("token")).groupBy("token").agg(F.count("*").alias("n"))
    each = rules.select("rule", "tokens", F.explode("tokens").alias("token")).join(often, "token")
    posted = each.groupBy("rule").agg(F.min(F.struct("n", "token")).alias("rarest"), F.first("tokens").alias("needed")).select("rule", F.col("rarest.token").alias("token"), "needed")
    held = token_sets.select("key", "tokens", F.explode("tokens").alias("token")).join(posted, "token")
    full = held.where(F.size(F.array_except("needed", "tokens")) == 0)
    return full.groupBy("key").agg(F.count("*").alias("hits"))


def judge_urls(pages: DataFrame, labels: DataFrame, id_col: str = "page_id", url_col: str = "url", label_id: str = "doc_id", rules=DEFAULT_RULES, min_support: float = 0.002, min_confidence: float = 0.5, min_count: int = 5, min_lift: float = 1.5) -> DataFrame:
    """Rows (id, host, path, rule, verdict, mined boolean), one for each row of ``pages``.

    A label with quality 0 or toxic 1 is a bad one; several labels of one page count as bad if any is. A null URL or one
    without a scheme has empty host and path, fits no rule and is allowed; the same holds without labels. Null ids and
    repeated rows pass through; URLs are read whole;
    further columns are ignored; an empty table gives no rows.
    """
    url = F.col(url_col)
    split = pages.select(F.col(id_col).alias("id"), url.alias("url"), host_of(url).alias("host"), path_of(url).alias("path"))
    rule, verdict = fixed_rule(F.col("host"), F.col("path"), rules)
    tokens = url_tokens(F.col("url"), F.col("host"), F.col("path"))
    judged = split.select("id", "host", "path", rule.alias("rule"), verdict.alias("fixed"), F.array_sort(tokens).alias("tokens")).withColumn("key", F.sha2(F.to_json("tokens"), 256))
    bad = labels.groupBy(F.col(label_id).alias("id")).agg(F.max((F.coalesce("quality", F.lit(1)) == 0) | (F.coalesce("toxic", F.lit(0)) == 1)).alias("bad"))
    mined = mine_rules(judged.join(bad, "id").select("tokens", "bad"), min_support, min_confidence, min_count, min_lift)
    if mined is None:
        hit = judged.withColumn("hits", F.lit(None).cast("long"))
    else:
        sets = judged.where("fixed is null").groupBy("key").agg(F.first("tokens").alias("tokens"))
        hit = judged.join(matching_rules(to_items(sets, mined[1]), mined[0]), "key", "left")
    return hit.select(
        "id", "host", "path", "rule",
        F.coalesce("fixed", F.when(F.col("hits").isNotNull(), "block").otherwise("allow")).alias("verdict"),
        F.col("hits").isNotNull().alias("mined"),
    )
