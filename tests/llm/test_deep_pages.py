"""Containers below long class lists keep paths of their own."""

from quorumgrad.llm import html_text


def page(i):
    wrap = "".join(f'<div class="{" ".join(f"utility-{chr(97 + k)}-class-{chr(97 + d)}" for k in range(8))}">' for d in range(14))
    words = " ".join(f"article{i} sentence number {k}." for k in range(40))
    return f'<html><body>{wrap}<div class="story"><p>{words}</p></div><div class="column"><p>Other notices {i}.</p></div>{"</div>" * 14}</body></html>', words


def test_side_column_below_long_paths_stays_out():
    pages = [page(i) for i in range(3)]
    votes = {html_text.best_path(h) for h, _ in pages}
    assert len(votes) == 1
    (path,) = votes
    for html, words in pages:
        assert html_text.extract(html, path) == words
    assert len(path) <= html_text.MOST_PATH
