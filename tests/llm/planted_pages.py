"""Pages with a known main text, in several styles of markup; helpers of the tests."""

import random

_WORDS = "river stone market window yellow carry morning between letter garden signal harbour winter paper copper gentle number travel follow bridge answer silent field doctor music".split()


def sentence(r, lo=7, hi=18):
    w = [r.choice(_WORDS) for _ in range(r.randrange(lo, hi))]
    return " ".join(w).capitalize() + r.choice("...!?")


def paragraph(r):
    return " ".join(sentence(r) for _ in range(r.randrange(1, 5)))


def links(r, n, tag="li"):
    return "".join(f'<{tag}><a href="/{r.choice(_WORDS)}">{" ".join(r.choice(_WORDS) for _ in range(r.randrange(1, 4)))}</a></{tag}>' for _ in range(n))


def body(r):
    """(markup, texts) of an article's inside: paragraphs, short ones too, lists with links, captions, headings."""
    html, texts = [], []

    def put(markup, text):
        html.append(markup.format(text)), texts.append(text)

    for _ in range(r.randrange(3, 9)):
        kind = r.random()
        if kind < 0.55:
            put("<p>{}</p>", paragraph(r))
        elif kind < 0.65:
            put("<p>{}</p>", r.choice(_WORDS).capitalize() + r.choice([".", "", "!"]))
        elif kind < 0.75:
            put("<h2>{}</h2>", " ".join(r.choice(_WORDS) for _ in range(3)).capitalize())
            put("<p>{}</p>", paragraph(r))
        elif kind < 0.85:
            items = [" ".join(r.choice(_WORDS) for _ in range(r.randrange(2, 7))) for _ in range(3)]
            html.append("<ul>" + "".join(f'<li><a href="/x">{x}</a></li>' if r.random() < 0.3 else f"<li>{x}</li>" for x in items) + "</ul>")
            texts.extend(items)
        elif kind < 0.93:
            put('<figure><img src="a.png"><figcaption>{}</figcaption></figure>', sentence(r, 3, 7))
        else:
            put(f'<div class="{r.choice(["meta", "tags", "note-search", "legal", "related-reading"])}"><p>{{}}</p></div>', paragraph(r))
    return "".join(html), texts


def page(seed):
    r = random.Random(seed)
    title = sentence(r, 3, 8)[:-1]
    inside, texts = body(r)
    nav = f"<nav><ul>{links(r, 6)}</ul></nav>" if r.random() < 0.6 else f'<div class="{r.choice(["menu", "navbar", "x7"])}"><ul>{links(r, 6)}</ul></div>'
    advert = f'<div class="{r.choice(["ad", "advert-box", "sponsored", "promo"])}"><p>{sentence(r)}</p></div>'
    cookie = f'<div id="cookie-banner"><p>{sentence(r)}</p><button>Accept all</button></div>'
    side = f"<aside><h3>Popular</h3>{paragraph(r)}</aside>" if r.random() < 0.5 else f'<div class="sidebar"><h3>Popular</h3><ul>{links(r, 4)}</ul><p>{sentence(r)}</p></div>'
    comments = '<section class="comments"><h3>Comments</h3>' + "".join(f"<div><p>{paragraph(r)}</p></div>" for _ in range(r.randrange(0, 4))) + "<form><p>Leave a reply</p><textarea>x</textarea></form></section>"
    footer = f"<footer><p>{sentence(r)}</p><ul>{links(r, 3)}</ul></footer>" if r.random() < 0.6 else f'<div class="footer">{links(r, 3, "span")} All rights reserved</div>'
    style = r.randrange(4)
    if style == 0:
        core = f"<article><h1>{title}</h1>{inside}{advert if r.random() < 0.4 else ''}</article>"
    elif style == 1:
        core = f'<div class="post-header"><h1>{title}</h1></div><article>{inside}</article>'
    elif style == 2:
        core = f'<div id="content"><div class="post-body"><h1>{title}</h1>{inside}</div></div>'
    else:
        core = f"<main><header><h1>{title}</h1></header><section>{inside}</section></main>"
    site = f'<header><a href="/">{r.choice(_WORDS).capitalize()} Daily</a></header>' if r.random() < 0.7 else ""
    html = f"<html><head><title>{title}</title><style>p{{}}</style></head><body>{cookie if r.random() < 0.5 else ''}{site}{nav}{advert if r.random() < 0.5 else ''}{core}{comments}{side}{footer}<script>var x = '<p>no</p>';</script></body></html>"
    return html, [title, *texts]
