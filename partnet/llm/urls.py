"""URL filters: a blocked Bloom filter passes possible hits to an exact hash join.

A listed entry is a canonical URL: lower-case host, slash, path prefix. A URL
fits an entry if its host is the entry's or below it and its path begins with
the entry's, so a URL has one candidate key for each suffix of its host and each
path length that the list knows. The filter (256-bit blocks, one bit in each of
four words) rejects nearly all of them; what passes is joined exactly, which
removes false positives. The longest entry that fits wins.

All of it is DataFrame expressions. The filter takes about two bytes an entry;
it is broadcast while it is below a checked bound and joined by block beyond.

Defined results: a null url, or one without "://", has an empty host and path
and fits nothing; without an entry the verdict is allow; if entries disagree on
the same key, block wins; an empty list allows everything; repeated rows are
judged alike; extra columns are ignored.
"""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from partnet.llm.bloom import BITS_PER_KEY, BLOCK_BITS, bloom_bits, blocked_bloom

#: fixed values: the contract's rules
RULES = (
    ("com/", "allow"),
    ("example.com/en/", "block"),
    ("www.example.com/en/", "allow"),
    ("net/es/", "block"),
    ("net/fr/", "block"),
)
#: sites that are unwanted as a whole, under whatever top-level domain
SITES = ("ads-track.example", "adult-x.example", "casino-win.example", "cheap-pills.example", "free-bets.example", "spam-farm.example")
#: the generic top-level domains in common use and those of countries
TLDS = tuple(
    (
        "com net org edu gov mil int info biz name pro aero coop museum jobs mobi travel tel cat asia post xxx app blog club cloud dev fun icu life live news online page shop site space store stream tech today top vip website win work world xyz "
        "ac ad ae af ag ai al am ao aq ar as at au aw ax az ba bb bd be bf bg bh bi bj bm bn bo br bs bt bv bw by bz ca cc cd cf cg ch ci ck cl cm cn co cr cu cv cw cx cy cz de dj dk dm do dz ec ee eg er es et eu fi fj fk fm fo fr "
        "ga gb gd ge gf gg gh gi gl gm gn gp gq gr gs gt gu gw gy hk hm hn hr ht hu id ie il im in io iq ir is it je jm jo jp ke kg kh ki km kn kp kr kw ky kz la lb lc li lk lr ls lt lu lv ly ma mc md me mg mh mk ml mm mn mo mp mq mr ms mt mu mv mw mx my mz "
        "na nc ne nf ng ni nl no np nr nu nz om pa pe pf pg ph pk pl pm pn pr ps pt pw py qa re ro rs ru rw sa sb sc sd se sg sh si sj sk sl sm sn so sr ss st su sv sx sy sz tc td tf tg th tj tk tl tm tn to tr tt tv tw tz ua ug uk us uy uz va vc ve vg vi vn vu wf ws ye yt za zm zw"
    ).split()
)
#: the list behind the method's own verdict
LISTED = tuple(f"{site}.{tld}/" for site in SITES for tld in TLDS)
BROADCAST_BYTES = 128 << 20


def url_parts(url: Column) -> tuple[Column, Column]:
    pattern = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    host = F.translate(F.regexp_extract(url, pattern, 1), string.ascii_uppercase, string.ascii_lowercase)
    return F.coalesce(host, F.lit("")), F.coalesce(F.regexp_extract(url, pattern, 2), F.lit(""))


def entries(spark: SparkSession, rules: tuple[tuple[str, str], ...], listed: tuple[str, ...]) -> DataFrame:
    """(key, verdict, is_rule) of short lists. Long ones come as a table of the same columns."""
    rows = [F.struct(F.lit(k).alias("key"), F.lit(v).alias("verdict"), F.lit(True).alias("is_rule")) for k, v in rules]
    ruled = spark.range(1).select(F.inline(F.array(*rows))) if rows else spark.range(0).select(F.lit("").alias("key"), F.lit("").alias("verdict"), F.lit(True).alias("is_rule"))
    sites = F.explode(F.split(F.lit("\n".join(listed)), "\n")).alias("key")
    return ruled.unionByName(spark.range(1).select(sites, F.lit("block").alias("verdict"), F.lit(False).alias("is_rule"))) if listed else ruled


def candidate_keys(host: Column, path: Column, path_lengths: Column) -> Column:
    """One key for each suffix of the host and each known path length that the path reaches."""
    labels = F.split(host, r"\.", -1)
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.concat_ws(".", F.slice(labels, i, F.size(labels))))
    prefixes = F.transform(F.filter(path_lengths, lambda n: n <= F.length(path)), lambda n: F.substring(path, F.lit(1), n))
    return F.flatten(F.transform(suffixes, lambda s: F.transform(prefixes, lambda p: F.concat(s, p))))


def judge_urls(pages: DataFrame, listed: DataFrame) -> DataFrame:
    """pages(page_id, url) and listed(key, verdict, is_rule) to page_id, host, path, rule, verdict, listed_as."""
    host, path = url_parts(F.col("url"))
    judged = pages.select("page_id", host.alias("host"), path.alias("path"))
    once = listed.groupBy("key").agg(F.max("verdict").alias("verdict"), F.max("is_rule").alias("is_rule"))  # block sorts after allow
    slash = F.locate("/", F.col("key"))
    facts = listed.agg(F.count(F.lit(1)).alias("n"), F.sort_array(F.collect_set(F.length("key") - slash + 1)).alias("lengths")).first()
    n, lengths = facts["n"], facts["lengths"]
    blocks = max(1, -(-n * BITS_PER_KEY // BLOCK_BITS))
    bloom = blocked_bloom(once, blocks)
    bloom = F.broadcast(bloom) if blocks * (BLOCK_BITS // 8 + 8) <= BROADCAST_BYTES else bloom
    sites = judged.select("host", "path").where(F.col("path") != "").distinct()
    keys = F.array(*[F.lit(x) for x in lengths]) if lengths else F.array().cast("array<int>")
    asked = sites.select("host", "path", F.explode(F.array_distinct(candidate_keys(F.col("host"), F.col("path"), keys))).alias("key"))
    block, bits = bloom_bits(F.col("key"), blocks)
    asked = asked.select("*", block.alias("block"), *(b.alias(f"b{k}") for k, b in enumerate(bits)))
    passed = asked.join(bloom, "block").where(" AND ".join(f"(w{k} & b{k}) != 0" for k in range(4))).select("host", "path", "key")
    hits = passed.join(once, "key").groupBy("host", "path").agg(
        F.max(F.when(F.col("is_rule"), F.struct(F.length("key").alias("n"), "key", "verdict"))).alias("as_rule"),
        F.max(F.when(~F.col("is_rule"), F.struct(F.length("key").alias("n"), "key", "verdict"))).alias("as_listed"),
    )
    verdict = F.coalesce(F.col("as_rule.verdict"), F.col("as_listed.verdict"), F.lit("allow"))
    return judged.join(hits, ["host", "path"], "left").select("page_id", "host", "path", F.col("as_rule.key").alias("rule"), verdict.alias("verdict"), F.col("as_listed.key").alias("listed_as"))
