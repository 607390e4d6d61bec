"""Class names that only mention boilerplate, and names on the wrappers of the content."""

import pytest

from partnet.llm.html_text import main_text, names_boilerplate

BODY = "<h1 class=page-header>Head</h1><p>Body text that is long enough to count here.</p>"
WANT = "Head\nBody text that is long enough to count here."


@pytest.mark.parametrize("name", ["container has-sidebar", "with-sidebar", "post comments-open", "share-price", "post-sidebar", "page-header"])
def test_content_under_such_a_name_is_kept(name):
    assert main_text(f"<div class='{name}'><article>{BODY}</article></div>") == WANT
    assert main_text(f"<article class='{name}'>{BODY}</article>") == WANT
    assert main_text(f"<nav>menu</nav><main id='{name}'>{BODY}</main>") == WANT


@pytest.mark.parametrize("name", ["ad", "sidebar", "Cookie-Banner", "related-posts", "main_menu", "site-footer", "comment-list", "ad-slot-3", "side-bar"])
def test_boilerplate_names_still_drop(name):
    assert names_boilerplate(name)
    assert main_text(f"<article>{BODY}<div class='{name}'><p>gone</p></div></article>") == WANT
    assert main_text(f"<article>{BODY}</article><div class='{name}'><article><p>teaser</p></article></div>") == WANT


def test_teasers_do_not_replace_a_page_without_an_article():
    text = WANT.split("\n")[1]
    assert main_text(f"<div><p>{text}</p></div><div class=related><article><p>teaser</p></article></div>") == text
