"""Pages that omit the end tag of their head."""

from __future__ import annotations

import pytest
from tissuemap.llm import html_extract

STORY = "<article><p>First part.<p>Second part.</article>"


@pytest.mark.parametrize(
    "head",
    [
        "<head><meta charset=utf-8><title>t</title><body>",
        "<head><title>t</title><link rel=x href=y><script>var a = '<p>';</script><style>p{}</style>\n<noscript>n</noscript>",
        "<head>\n<!-- note -->\n<body class=page>",
        "<HEAD><BODY>",
        "<head><head><body>",
        "<head></head><body>",
        "<title>t</title><body>",
    ],
)
def test_text_after_an_open_head(head):
    assert html_extract.extract(f"<!doctype html><html>{head}{STORY}") == "First part.\n\nSecond part."


def test_text_and_inline_tags_end_a_head():
    assert html_extract.extract("<head><title>t</title>plain words") == "plain words"
    assert html_extract.extract("<head><title>t</title><b>bold</b> words") == "bold words"
    assert html_extract.extract("<head><title>t</title> \n </head> <body>after") == "after"
