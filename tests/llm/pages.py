"""Pages put together from known parts."""

import html
import re


def planted_page(rng):
    """A page put together from known parts: its html and the text of its article."""
    word = lambda: "".join(rng.choices("abcdefghijklmnoprstuvw", k=rng.randrange(2, 9)))
    prose = lambda n: " ".join(word() + ("," if rng.random() < 0.08 else "") for _ in range(n)).rstrip(",") + "."
    gap = lambda: rng.choice([" ", "\n", "\n  ", "\t"])
    noise = {
        "menu": lambda: "<nav><ul>" + "".join(f"<li><a href='/{word()}'>{word()}</a>" for _ in range(rng.randrange(3, 9))) + "</ul></nav>",
        "header": lambda: f"<header><div class=logo>{word()}</div><p>{prose(5)}</p></header>",
        "footer": lambda: f"<footer><p>&copy; {prose(8)}</p></footer>",
        "sidebar": lambda: f'<div class="{rng.choice(["sidebar", "widget left", "related-posts"])}"><h3>{word()}</h3><p>{prose(14)}</p></div>',
        "aside": lambda: f"<aside><p>{prose(20)}</p></aside>",
        "notice": lambda: f'<div id="cookie-{rng.choice(["banner", "notice"])}">{prose(12)}<button>ok</button></div>',
        "advert": lambda: f'<div class="ad-slot advert"><p>{prose(15)}</p></div>',
        "form": lambda: f"<form><label>{word()}</label><input name=q><p>{prose(6)}</p></form>",
        "script": lambda: f"<script>var x = '<p>{prose(9)}</p>'; if (a < b) c();</script>",
        "style": lambda: "<style>p > a { color: red }</style>",
        "comment": lambda: f"<!-- {prose(9)} <p>no</p> -->",
        "hidden": lambda: f"<div hidden><p>{prose(9)}</p></div>",
    }
    blocks, source = [], []
    for _ in range(rng.randrange(3, 9)):
        kind = rng.choice(["p", "p", "p", "p", "h2", "list", "quote", "pre"])
        if kind == "list":
            items = [prose(rng.randrange(4, 12)) for _ in range(rng.randrange(2, 5))]
            blocks += items
            source.append("<ul>" + "".join(f"<li>{i}" + rng.choice(["", "</li>"]) for i in items) + "</ul>")
            continue
        words = prose(rng.randrange(25, 90) if kind == "p" else rng.randrange(3, 20)).split(" ")
        shown = []
        for w in words:
            r = rng.random()
            shown.append(f"<b>{w}</b>" if r < 0.05 else f'<a href="#">{w}</a>' if r < 0.07 else w + "&amp;" if r < 0.09 else w)
        plain = " ".join(html.unescape(re.sub("<[^>]*>", "", w)) for w in shown)
        blocks.append(plain)
        tag = {"p": "p", "h2": "h2", "quote": "blockquote", "pre": "p"}[kind]
        source.append(f"<{tag}>{gap()}{gap().join(shown)}{gap()}" + ("" if tag == "p" and rng.random() < 0.3 else f"</{tag}>"))
        if rng.random() < 0.25:
            source.append(rng.choice([noise["script"], noise["comment"], noise["advert"], noise["form"], noise["style"]])())
    article = rng.choice(['<article>{}</article>', '<div class="post-content">{}</div>', '<main><div>{}</div></main>', '<div id="main"><section>{}</section></div>'])
    body = article.format(gap().join(source))
    before = [noise[k]() for k in rng.sample(["menu", "header", "notice", "sidebar", "script", "comment", "hidden"], rng.randrange(2, 6))]
    after = [noise[k]() for k in rng.sample(["footer", "sidebar", "aside", "form", "advert", "style"], rng.randrange(2, 5))]
    replies = f'<div id="comments"><h3>{word()}</h3>' + "".join(f'<div class="comment"><p>{prose(rng.randrange(10, 60))}</p></div>' for _ in range(rng.randrange(0, 4))) + "</div>"
    page = f"<!DOCTYPE html><html><head><title>{word()}</title></head><body>{''.join(before)}{body}{replies}{''.join(after)}</body></html>"
    return page, "\n".join(blocks)
