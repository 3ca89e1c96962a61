"""What follows an odd tag stays in the scan."""

import pytest

from levelindex.llm import html_main_text


@pytest.mark.parametrize("odd", ["I </3 x> you", "a </ b> c", "a </> c", "<p title='don't'>it", "<img alt=\"5\" screen\">it"])
def test_text_after_odd_tags(odd):
    page = f"<p>one {odd}</p><p>the rest of the page</p>"
    pieces = "".join(text for _, text, name, _ in html_main_text.tokens_of(page) if name is None)
    assert pieces.startswith("one ") and pieces.endswith("the rest of the page")


def test_no_tag_follows():
    for text in ("love </3 and more", "love </é and more"):
        assert "".join(t for _, t, name, _ in html_main_text.tokens_of("<p>" + text) if name is None) == text
