"""URL filters: allow and block rules, and a blocked Bloom filter of listed URLs before an exact hash join.

Each listed canonical URL sets 8 bits in one block of 256, so a test reads one block. The filter has a
number of blocks that follows the list up to MAX_BLOCKS (32 bytes each), which bounds what is
broadcast; a longer list only lets more URLs through to the exact join on the canonical form, which
removes all false positives. URLs that the filter rules out are never shuffled.

Defined results: a null URL, or one without ``://``, has an empty host and path, fits no rule, is on no
list and is allowed; repeated rows give a row each.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
ALLOW, BLOCK = "allow", "block"
WORDS, SET_BITS = 4, 8
MAX_BLOCKS = 1 << 20
KEYS_A_BLOCK = 16

#: (verdict, host, path) (fixed values).
RULES = (
    (ALLOW, "com", "/"),
    (BLOCK, "example.com", "/en/"),
    (ALLOW, "www.example.com", "/en/"),
    (BLOCK, "net", "/es/"),
    (BLOCK, "net", "/fr/"),
)
#: Host labels whose pages make up the default list (fixed values).
LISTED_LABELS = ("casino-win", "spam-farm", "adult-x", "cheap-pills", "ads-track", "free-bets")
#: Query parameters that don't change the page (fixed values).
TRACKING = "utm_[a-z]+|ref|fbclid|gclid"


def host_of(url: Column) -> Column:
    """What follows the first :// up to a slash, a question mark, a hash or the end, A-Z in lower case."""
    return F.translate(F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def canonical(url: Column) -> Column:
    """Host and path without www., standard ports and closing slashes, with the parameters that matter; null without ://."""
    host = F.regexp_replace(F.regexp_replace(host_of(url), r"^www\.", ""), r":(80|443)$", "")
    path = F.regexp_replace(path_of(url), r"/+$", "")
    query = F.regexp_extract(url, r"(?s)^.*?://[^?#]*\?([^#]*)", 1)
    kept = F.array_join(
        F.array_sort(F.filter(F.split(query, "&"), lambda p: (p != "") & ~p.rlike(f"^({TRACKING})(=|$)"))), "&"
    )
    whole = F.concat(host, path, F.when(kept != "", F.concat(F.lit("?"), kept)).otherwise(F.lit("")))
    return F.when(F.instr(url, "://") > 0, whole)


def rule_of(host: Column, path: Column, rules: tuple = RULES) -> Column:
    """The longest rule that fits as struct(rule, verdict), or null."""
    out = None
    for verdict, h, p in sorted(rules, key=lambda r: -len(r[1] + r[2])):
        fits = ((host == h) | host.endswith(f".{h}")) & path.startswith(p)
        found = F.struct(F.lit(h + p).alias("rule"), F.lit(verdict).alias("verdict"))
        out = F.when(fits, found) if out is None else out.when(fits, found)
    return out if out is not None else F.lit(None).cast("struct<rule:string,verdict:string>")


def block_count(listed: int) -> int:
    """The power of two that gives each block KEYS_A_BLOCK keys at most, within the bound."""
    return min(1 << ((max(listed, 1) - 1) // KEYS_A_BLOCK).bit_length(), MAX_BLOCKS)


def _bits(key: Column) -> list[Column]:
    """Bit masks of a key for the words of its block."""
    h = F.xxhash64(key, F.lit(1))
    spots = [F.shiftrightunsigned(h, 8 * k).bitwiseAND(F.lit(255)) for k in range(SET_BITS)]
    masks = []
    for w in range(WORDS):
        mask = F.lit(0).cast("long")
        for s in spots:
            one = F.when(F.shiftright(s, 6) == w, F.call_function("shiftleft", F.lit(1).cast("long"), s.bitwiseAND(F.lit(63)).cast("int"))).otherwise(F.lit(0).cast("long"))
            mask = mask.bitwiseOR(one)
        masks.append(mask)
    return masks


def bloom_filter(keys: DataFrame, key: str, blocks: int) -> DataFrame:
    """(block, w0..w3): at most `blocks` rows."""
    spot = F.pmod(F.xxhash64(F.col(key)), F.lit(blocks))
    marked = keys.where(F.col(key).isNotNull()).select(spot.alias("block"), *(m.alias(f"w{i}") for i, m in enumerate(_bits(F.col(key)))))
    return marked.groupBy("block").agg(*(F.bit_or(f"w{i}").alias(f"w{i}") for i in range(WORDS)))


def on_list(urls: DataFrame, key: str, listed: DataFrame, listed_key: str) -> DataFrame:
    """urls with the boolean _kb_listed: whether its key is among the keys of listed. Null keys are on no list."""
    names = listed.select(F.col(listed_key).alias("_kb_key")).where("_kb_key is not null").distinct()
    blocks = block_count(names.count())
    bloom = bloom_filter(names, "_kb_key", blocks).withColumnRenamed("block", "_kb_block")
    probe = urls.withColumn("_kb_block", F.pmod(F.xxhash64(F.col(key)), F.lit(blocks)))
    joined = probe.join(F.broadcast(bloom), "_kb_block", "left")
    possible = F.col(key).isNotNull() & F.col("w0").isNotNull()
    for i, m in enumerate(_bits(F.col(key))):
        possible &= F.col(f"w{i}").bitwiseAND(m) == m
    tested = joined.withColumn("_kb_maybe", F.coalesce(possible, F.lit(False)))
    out = tested.where("NOT _kb_maybe").select(*urls.columns, F.lit(False).alias("_kb_listed"))
    exact = (
        tested.where("_kb_maybe")
        .select(*urls.columns)
        .join(names.withColumn("_kb_hit", F.lit(True)), F.col(key) == F.col("_kb_key"), "left")
        .select(*urls.columns, F.coalesce("_kb_hit", F.lit(False)).alias("_kb_listed"))
    )
    return out.union(exact)


def default_list(pages: DataFrame) -> DataFrame:
    """(url): the canonical URLs of the pages whose host has a listed label."""
    labels = "|".join(LISTED_LABELS)
    return pages.where(host_of(F.col("url")).rlike(rf"(^|\.)({labels})(\.|$)")).select(canonical(F.col("url")).alias("url")).distinct()


def verdicts(pages: DataFrame, listed: DataFrame, rules: tuple = RULES) -> DataFrame:
    """(page_id, host, path, rule, verdict, listed) for every row of pages; listed has canonical URLs in url."""
    named = pages.select(
        "page_id",
        host_of(F.col("url")).alias("host"),
        path_of(F.col("url")).alias("path"),
        canonical(F.col("url")).alias("_kb_canonical"),
    )
    checked = on_list(named, "_kb_canonical", listed, "url").withColumn("_kb_rule", rule_of(F.col("host"), F.col("path"), rules))
    return checked.select(
        "page_id",
        "host",
        "path",
        F.col("_kb_rule.rule").alias("rule"),
        F.coalesce(F.col("_kb_rule.verdict"), F.when(F.col("_kb_listed"), BLOCK).otherwise(ALLOW)).alias("verdict"),
        F.col("_kb_listed").alias("listed"),
    )
