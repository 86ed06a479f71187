"""Noise words on elements around the article do not cut it."""

import pytest

from gainclust.llm import html_text

TEXT = " ".join(f"Sentence number {i} of the article says something of its own, and says it at length." for i in range(12))
BODY = "".join(f"<p>{x.strip()}.</p>" for x in TEXT.split(".") if x.strip())
SMALL = "<div class='ad'>Buy this now</div><div class='sidebar'><a href='x'>Other</a> news of today</div>"


@pytest.mark.parametrize(
    "page",
    [
        f"<div class='layout with-sidebar'><article>{BODY}</article>{SMALL}</div>",
        f"<div id='content' class='no-sidebar'>{BODY}</div>{SMALL}",
        f"<div class='post has-comments'>{BODY}</div>{SMALL}",
        f"<form action='x'><div>{BODY}</div>{SMALL}</form>",
        f"<div class='widget'><article>{BODY}</article></div>{SMALL}",
        f"<div class='overlay'><div class='banner'>{BODY}</div></div>{SMALL}",
    ],
)
def test_article_survives_noise_words_around_it(page):
    assert html_text.main_text(f"<html><body><nav><a href='/'>Home</a></nav>{page}<footer>End</footer></body></html>") == " ".join(TEXT.split())


def test_noise_beside_the_article_still_goes():
    comments = "<div class='comments'>" + "".join(f"<article class='c'>Reader {i} likes this very much indeed.</article>" for i in range(30)) + "</div>"
    form = "<form>Sign up for news: <input name='q'></form>"
    assert html_text.main_text(f"<body><article>{BODY}</article>{comments}{form}{SMALL}</body>") == " ".join(TEXT.split())
    assert html_text.main_text(f"<body><div class='post'>{BODY}</div>{form}{SMALL}</body>") == " ".join(TEXT.split())
