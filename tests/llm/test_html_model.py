"""Long pages, kept elements and exact marginals among many siblings."""

from __future__ import annotations

import numpy as np
import pytest


def test_marginals_are_exact_among_many_siblings():
    from locveil.llm import html_extract as h

    nodes = h.parse("<body><div>" + "<p>aa bb</p>" * 100 + "</div></body>")
    feats, edge = h.features(nodes)
    rng = np.random.default_rng(2)
    w, e = rng.normal(size=h.N_FEATURES), rng.normal(size=(h.N_EDGES, 2, 2))
    belief, _ = h.marginals(nodes, feats, edge, w, e)
    # Given the state of the div the paragraphs are independent: two sums of products.
    div = next(i for i, n in enumerate(nodes) if n.tag == "div")
    above = {}
    for y in (0, 1):
        chain = {None: 1.0}
        at, path = div, []
        while at >= 0:
            path.append(at)
            at = nodes[at].parent
        chain = None
        for i in reversed(path):
            own = np.exp(np.array([0.0, w[feats[i]].sum()]))
            chain = own if chain is None else (chain @ np.exp(e[edge[i]])) * own
        above[y] = chain[y]
    below = {y: 1.0 for y in (0, 1)}
    for c in nodes[div].children:
        for y in (0, 1):
            below[y] *= np.exp(e[edge[c], y, 0]) + np.exp(e[edge[c], y, 1] + w[feats[c]].sum())
    total = above[0] * below[0] + above[1] * below[1]
    assert np.isclose(belief[div], above[1] * below[1] / total)


@pytest.mark.parametrize("open_,close", [("<article>", "</article>"), ("<div>", "</div>"), ("", "")])
def test_long_pages_stay_whole(open_, close):
    from locveil.llm.html_extract import trained

    for n in (30, 300, 20000):
        page = f"<html><body><nav><ul>{'<li><a href=#>x y</a></li>' * 8}</ul></nav>{open_}{'<p>some words that go on here.</p>' * n}{close}<footer>c</footer></body></html>"
        assert trained().text(page) == " ".join(["some words that go on here."] * n)


def test_many_comments_stay_out():
    from locveil.llm.html_extract import trained

    story = "<article><p>main text that is rather long and nice to read by all.</p></article>"
    for n in (3, 300, 5000):
        page = f"<html><body>{story}<section class=comments>{'<p>I see this in another way.</p>' * n}</section></body></html>"
        assert trained().text(page) == "main text that is rather long and nice to read by all."


def test_elements_that_hold_text_are_kept():
    from locveil.llm.html_extract import trained

    page = "<article><p>Start of a longer paragraph of text, İİİİ.</p><SCRIPT>var x;</Script><p>Next has <math><mi>E</mi><mo>=</mo><mi>m</mi></math> in it, <xmp><b>raw</b></xmp> too.</p><p>Third <svg><text>pic</text></svg> <object>obj</object> <noscript>nos</noscript> paragraph.</p></article>"
    assert trained().text(page * 1) == "Start of a longer paragraph of text, İİİİ. Next has E=m in it, <b>raw</b> too. Third pic obj nos paragraph."
    long = "<article><p>" + "İ" * 40 + " opens it.</p><script>x</script><p>The whole next paragraph stays here.</p></article>"
    assert trained().text(long).endswith("opens it. The whole next paragraph stays here.")


def test_text_in_nothing_but_wrappers_is_no_article_when_deep():
    from locveil.llm.html_extract import trained

    assert trained().text("<div>" * 5000 + "some words here" + "</div>" * 5000) == ""
