"""The method's own verdict of the URL filter in tables whose unwanted sites have other top-level domains."""

import pytest
from pyspark.sql import functions as F

from partnet.llm import urls

ODD = r"(^|\.)(ads-track|adult-x|casino-win|cheap-pills|free-bets|spam-farm)\.example\.[a-z]+$"


@pytest.mark.parametrize("table", ["sf0.001", "sf0.01", "sf0.1"])
def test_unwanted_sites_are_listed_whatever_their_top_level_domain(spark, table):
    pages = spark.read.parquet(f"/root/testdata/{table}/pages.parquet")
    judged = urls.judge_urls(pages, urls.entries(spark, urls.RULES, urls.LISTED)).where(F.col("host").rlike(ODD)).collect()
    assert judged and all(r.listed_as is not None for r in judged)
    assert all(r.verdict == "block" for r in judged if r.rule is None)
    alone = urls.judge_urls(pages, urls.entries(spark, (), urls.LISTED))
    assert alone.where("verdict = 'block'").count() == len(judged)


def test_the_own_verdict_blocks_pages_of_a_larger_table(spark):
    pages = spark.read.parquet("/root/testdata/sf0.1/pages.parquet")
    judged = urls.judge_urls(pages, urls.entries(spark, urls.RULES, urls.LISTED))
    assert judged.where("rule IS NULL AND verdict = 'block'").count() > 0


def test_every_site_under_other_domains(spark):
    hosts = [f"{www}{site}.{tld}" for site in urls.SITES for tld in ("net", "de", "xyz") for www in ("", "m.")]
    pages = spark.createDataFrame([(k, f"https://{h}/a") for k, h in enumerate(hosts)] + [(999, "https://not-spam-farm.example.org/a")], "page_id long, url string")
    verdicts = {r.page_id: r.verdict for r in urls.judge_urls(pages, urls.entries(spark, urls.RULES, urls.LISTED)).collect()}
    assert verdicts.pop(999) == "allow" and set(verdicts.values()) == {"block"}
