"""Pages that leave out the end of the head or the start of the body."""

from __future__ import annotations

import pytest

from locveil.llm.html_extract import parse

BODY = "<article><p>All of the text.</p></article>"


def _text(page):
    return "".join(t for n in parse(page) for _, t in n.items).strip()


@pytest.mark.parametrize(
    "page",
    [
        f"<html><head><title>T</title>{BODY}",
        f"<html><head><title>T</title><meta charset=x><link rel=y>\n{BODY}</html>",
        f"<html><head><script>var a = '<body>junk</head>';</script><!-- </head><body> --><style>p {{}}</style></head><body>{BODY}",
        f"<html><head><title>T</title></head><body>{BODY}</body></html>",
        f"<html><head><title>T</title><body>{BODY}</body></html>",
        "<html><head><title>T</title>All of the text.",
    ],
)
def test_head_ends_where_it_ends(page):
    assert _text(page) == "All of the text."
