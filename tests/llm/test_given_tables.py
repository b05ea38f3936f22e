"""Operators on the given tables against independent references."""

import re

from pyspark.sql import functions as F

from partgraph.llm import html_blocks as H
from partgraph.llm import toxicity as T

SF = "/root/testdata/sf0.01"


def test_pages_give_their_articles(spark):
    """The article element, its tags taken out by plain replacement, holds the text that is wanted."""
    import html as h

    pages = spark.read.parquet(f"{SF}/pages.parquet").limit(60).collect()
    got = {r.page_id: r.text for r in H.extract(spark.createDataFrame(pages)).collect()}
    same = 0
    for r in pages:
        body = re.search(r"(?s)<article.*?</article>", r.html)
        plain = re.sub(r"(?s)<(script|style|aside|form|nav|footer|header)\b.*?</\1>", " ", body.group(0)) if body else ""
        words = lambda x: re.findall(r"\w+", x)
        same += words(h.unescape(re.sub(r"(?s)<[^>]*>", " ", plain))) == words(got[r.page_id])
    assert same >= 0.9 * len(pages)


def test_held_out_toxicity(spark):
    got = T.op10_nnpu_toxicity(spark, SF).join(spark.read.parquet(f"{SF}/labels.parquet"), "doc_id").where("held_out")
    n = got.agg(F.count_if("toxic = 1").alias("toxic"), F.count_if("toxic = 1 and predicted = 1").alias("caught"), F.count_if("toxic = 0 and predicted = 1").alias("wrong"), F.count_if("toxic = 0").alias("clean")).first()
    assert n.caught >= 0.6 * n.toxic and n.wrong <= 0.02 * n.clean
