"""Op 1 where an article's parts stand beside one another, and where a head has no end."""

from hopwise.llm import html_extraction

LINE = "A long enough paragraph of the article, number {}, with many words in it, so that it is content."


def paragraphs(first, last):
    return "".join(f"<p>{LINE.format(i)}</p>" for i in range(first, last))


def test_nothing_of_the_article_is_lost():
    text = lambda n: "\n".join(LINE.format(i) for i in range(n))
    body, titled = paragraphs(0, 3), "Title\n" + text(3)
    cases = {
        f"<body><div id=content><section>{paragraphs(0, 6)}</section><section>{paragraphs(6, 10)}</section></div>": text(10),
        f"<body><div id=content><h1>Title</h1><div class=body>{body}</div></div>": titled,
        f"<main><h1>Title</h1><article>{body}</article></main>": titled,
        f"<div><article>{paragraphs(0, 6)}</article><article>{paragraphs(6, 10)}</article></div>": text(10),
        f"<head><title>t</title><meta charset=x><body>{body}</body>": text(3),
        f"<head><title>t</title><script>var a</script>{body}": text(3),
        f"<main><p>{LINE.format(0)}</p></main><div>An unmarked line of the page that is long enough to be taken</div>": text(1),
    }
    for html, want in cases.items():
        assert html_extraction.main_text(html) == want, html
