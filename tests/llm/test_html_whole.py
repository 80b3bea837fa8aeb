"""Content outside the heaviest container stays."""

from gradvb.llm.html_text import main_text


def paragraphs(name, n):
    return [f"{name} {k} says something, and then some more; it goes on for a while." for k in range(n)]


def page(tag, first, second):
    return "<html><body>" + "".join(f"<{tag}>" + "".join(f"<p>{p}</p>" for p in part) + f"</{tag}>" for part in (first, second)) + "</body></html>"


def test_second_container_and_second_article_stay():
    first, second = paragraphs("One", 13), paragraphs("Two", 7)
    for tag in ("div", "article"):
        assert main_text(page(tag, first, second)).split("\n") == first + second
