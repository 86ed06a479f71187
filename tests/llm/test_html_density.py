"""Density decides where tags and names tell nothing; long input takes time in proportion."""

import random
import time

import pytest

from gainclust.llm import html_text


def plain_page(rnd):
    """A page of div, p, ul and a only, without a telling tag or name; its article's paragraphs."""
    words = lambda n: " ".join("".join(rnd.choices("abcdefghij", k=rnd.randint(2, 9))) for _ in range(n))
    paras = [words(rnd.randint(20, 80)) for _ in range(rnd.randint(3, 9))]
    links = lambda n: "<div><ul>" + "".join(f"<li><a href='/{i}'>{words(2)}</a></li>" for i in range(n)) + "</ul></div>"
    body = "<div><div>" + "".join(f"<p>{p}</p>" for p in paras) + "</div></div>"
    small = f"<div><div><p>{words(4)}</p></div><div><a href='x'>{words(3)}</a></div></div>"
    return f"<html><body>{links(12)}{small}{body}{links(9)}<div>{words(5)}</div></body></html>", " ".join(paras)


def constant(self):
    total = [0.0] * len(self.tag)
    for p in self.parent[1:]:
        total[p] += 1.0
    return [1.0] * len(self.tag), total


def test_the_text_comes_through_the_densities(monkeypatch):
    pages = [plain_page(random.Random(i)) for i in range(60)]
    assert sum(html_text.main_text(h) == t for h, t in pages) == 60
    monkeypatch.setattr(html_text.Page, "densities", constant)
    assert sum(html_text.main_text(h) == t for h, t in pages) < 10


def test_sections_and_heading_beside_the_densest_part():
    para = "<p>Plain long prose that goes on for quite some while, as articles do.</p>"
    page = f"<body><div><a href=x>one</a> <a href=y>two</a></div><div><h1>On prose</h1><div>{para * 4}</div><div>{para * 6}</div></div></body>"
    assert html_text.main_text(page) == "On prose " + " ".join(["Plain long prose that goes on for quite some while, as articles do."] * 10)


@pytest.mark.parametrize("text", ["<a ", "<div>x", '<a "', "<p><table>" + "<div>x" * 50, "<b>x", "<", "<!--", "<a '<b \"", "<script>", "</p>", "<td>x<li>y", "&amp;", "<?", "<p>x"])
def test_long_input_takes_time_in_proportion(text):
    page = text * (1_000_000 // len(text))
    began = time.process_time()
    html_text.main_text(page)
    html_text.main_text(page + ">")
    assert time.process_time() - began < 30


def test_tags():
    got = [(n, a) for _, _, _, n, a in html_text.tags("a<b c='>'>d</b ><!-- <x> --><?y?>< z><p q=\"1'2\">e'<i>\"<u")]
    assert got == [("b", " c='>'"), ("b", " "), ("", ""), ("", ""), ("p", " q=\"1'2\""), ("i", "")]


def test_empty_table(spark):
    assert html_text.extract(spark.createDataFrame([], "page_id long, url string, html string")).collect() == []
