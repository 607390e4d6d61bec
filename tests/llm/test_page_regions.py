"""Pages on which the ratios decide: no article, several articles, short lines, stray divisions."""

import pytest

from partnet.llm.html_text import main_text

WORDS = "plain words of a paragraph that goes on for a while and has no link in it at all "
LONG = [f"{WORDS * 3}{k}." for k in range(4)]
MENU = "".join(f"<a href=/{k}>go {k}</a><br><i><b>x</b></i>" for k in range(3))
LINKS = "".join(f"<p><a href=/{k}><b><i>go {k}</i></b></a></p>" for k in range(12))


def paragraphs(texts):
    return "".join(f"<p>{x}</p>" for x in texts)


def test_threshold_decides():
    page = f"<body><div>{LINKS}</div><div><h1>Head</h1>{paragraphs(LONG)}<p>Bye.</p></div><div>{LINKS}</div></body>"
    want = "\n".join(["Head", *[x.strip() for x in LONG], "Bye."])
    assert main_text(page) == want
    assert main_text(page, level=1e9) == "" and "go 3" in main_text(page, level=-1e9)
    tagged = page.replace("<div><h1>", "<article><h1>").replace("Bye.</p></div>", "Bye.</p></article>")
    assert main_text(tagged) == want and main_text(tagged, level=1e9) == ""


@pytest.mark.parametrize("end", ["<p>Short end.</p><p>Bye.</p>", "<p>Short end.</p>Bye."])
def test_trailing_short_paragraphs_stay(end):
    page = f"<div>{LINKS}</div><p>{LONG[0]}</p><p>{LONG[1]}</p>{end}"
    assert main_text(page) == "\n".join([*LONG[:2], "Short end.", "Bye."])


def test_several_articles():
    teaser = "<article><p><a href=/t><b><i>tiny</i></b></a></p></article>"
    page = f"<article><h1>Head</h1>{paragraphs(LONG)}</article>{teaser * 3}"
    assert main_text(page) == "\n".join(["Head", *LONG])
    both = f"<article>{paragraphs(LONG[:2])}</article><article>{paragraphs(LONG[2:])}</article>"
    assert main_text(both) == "\n".join(LONG)


def test_nested_boxes_of_content_stay():
    page = f"<div>{MENU}</div><div><p>{LONG[0]}</p><div><p>Aside, but inside.</p></div><p>{LONG[1]}</p><p>{LONG[2]}</p></div>"
    assert main_text(page) == "\n".join([LONG[0], "Aside, but inside.", LONG[1], LONG[2]])
    assert main_text(f"<div class=wrap><div>{LINKS}</div><section>{paragraphs(LONG)}</section></div>") == "\n".join(LONG)


def test_whole_table_with_its_tags_taken_away(spark, sf):
    """Articles and menus as plain divisions: the ratios alone find the text that the article has."""
    from partnet.llm.html_text import extract_pages
    from pyspark.sql import functions as F

    pages = spark.read.parquet(f"{sf}/pages.parquet")
    bare = pages.withColumn("html", F.regexp_replace("html", "<(/?)(?:article|nav)>", "<$1div>"))
    want = {r.page_id: r.text for r in extract_pages(pages).collect()}
    found = {r.page_id: r.text for r in extract_pages(bare).collect()}
    # an article of a few words has no more text for each tag than a menu
    assert {k for k in want if found[k] != want[k]} <= {k for k, x in want.items() if len(x) < 100} and all(want.values())
    assert sum(found[k] == x for k, x in want.items()) >= 48
    assert not any(main_text(r.html, level=1e9) for r in pages.collect())
