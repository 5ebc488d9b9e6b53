"""Pages whose blocks are labelled by hand: the text of content blocks stands between ⟦ and ⟧.

Skeletons are written by hand after common page designs; prose, counts and captions vary by seed.
"""

from __future__ import annotations

import random

from boxsum.llm import html_extract

WORDS = "the river old house der Wald la maison people said that von une petite water light with und para muy grande town every year nothing les enfants many small winter road el camino across field never again quiet morning found written letters".split()


def prose(r: random.Random, low: int, high: int) -> str:
    out = []
    for _ in range(r.randint(1, max(1, high // 12))):
        w = [r.choice(WORDS) for _ in range(max(2, r.randint(low, high) // 2))]
        out.append(" ".join(w).capitalize() + r.choice([".", ".", ".", "!", "?"]))
    return " ".join(out)


def few(r: random.Random, n: int) -> str:
    return " ".join(r.choice(WORDS) for _ in range(n)).capitalize()


def paragraphs(r: random.Random, n: int, tag: str = "p") -> str:
    """Mostly long ones, some of a few words, some without an end."""
    made = [f"<{tag}>⟦{r.choice([prose(r, 20, 70), prose(r, 30, 90), prose(r, 8, 16), few(r, r.randint(1, 5))])}⟧</{tag}>" for _ in range(n)]
    return "".join(made)


def links(r: random.Random, n: int) -> str:
    return "<ul>" + "".join(f'<li><a href="/{i}">{few(r, r.randint(1, 4))}</a></li>' for i in range(n)) + "</ul>"


def article(r):
    return f"<html><body><header><h1>{few(r, r.randint(1, 6))}</h1><p>{prose(r, 8, 30)}</p>{links(r, 4)}</header><article><h1>⟦{few(r, 5)}⟧</h1>{paragraphs(r, 5)}<div class='ad-slot'>{few(r, 3)}</div><h2>⟦{few(r, 2)}⟧</h2>{paragraphs(r, 3)}<ul><li>⟦{few(r, 3)}⟧</li><li>⟦{prose(r, 6, 12)}⟧</li></ul></article><aside><p>{prose(r, 20, 50)}</p></aside><footer><p>&copy; {few(r, 4)}</p></footer></body></html>"


def blog(r):
    return f"<body><div id='top'><div class='logo'>{few(r, 2)}</div><div class='navbar'>{links(r, 6)}</div></div><div id='wrap'><div class='post'><h2>⟦{few(r, 4)}⟧</h2><div class='meta'>{few(r, 2)}</div><div class='entry-content'>{paragraphs(r, 6)}<blockquote>⟦{prose(r, 10, 30)}⟧</blockquote>{paragraphs(r, 2)}</div><div class='share-buttons'>{few(r, 2)}</div></div><div id='comments'><h3>{few(r, 2)}</h3>{''.join(f'<div class=comment><b>{few(r, 1)}</b><p>{prose(r, 20, 60)}</p></div>' for _ in range(r.randint(1, 6)))}</div></div><div class='sidebar'><p>{prose(r, 20, 40)}</p>{links(r, 5)}</div></body>"


def plain(r):
    """No element or name tells anything."""
    return f"<html><body><table><tr><td>{links(r, 7)}</td></tr></table><div><div><div>{paragraphs(r, 8)}</div></div></div><div><a href=a>{few(r, 2)}</a> | <a href=b>{few(r, 2)}</a> | <a href=c>{few(r, 3)}</a></div></body></html>"


def bare_lines(r):
    return f"<body><p><a href=/>{few(r, 2)}</a></p><h1>⟦{few(r, 4)}⟧</h1>{paragraphs(r, 4)}<hr><p>⟦{few(r, 3)}⟧</p><p>⟦{prose(r, 40, 60)}⟧</p><center><a href=x>{few(r, 1)}</a> <a href=y>{few(r, 1)}</a></center></body>"


def news(r):
    return f"<body><div class=masthead>{few(r, 3)}</div><nav>{links(r, 8)}</nav><main><div class=cookie-notice><p>{prose(r, 20, 40)}</p></div><section><h1>⟦{few(r, 6)}⟧</h1><p>⟦{few(r, 4)}⟧</p>{paragraphs(r, 7)}<figure><figcaption>⟦{few(r, 5)}⟧</figcaption></figure>{paragraphs(r, 2)}</section><section class='related'><h2>{few(r, 2)}</h2>{links(r, 4)}<p>{prose(r, 10, 24)}</p></section></main><footer>{few(r, 6)}. {few(r, 5)}.</footer></body>"


def manual(r):
    return f"<body><div role=navigation>{links(r, 10)}</div><div role=main><h1>⟦{few(r, 3)}⟧</h1>{paragraphs(r, 2)}<dl><dt>⟦{few(r, 1)}⟧</dt><dd>⟦{prose(r, 6, 20)}⟧</dd><dt>⟦{few(r, 2)}⟧</dt><dd>⟦{few(r, 4)}⟧</dd></dl><table><tr><td>⟦{few(r, 1)}⟧</td><td>⟦{few(r, 2)}⟧</td></tr></table>{paragraphs(r, 2)}</div><div role=contentinfo><p>{prose(r, 8, 20)}</p></div></body>"


def lists(r):
    return f"<body><header><p>{prose(r, 12, 40)}</p></header><div id=menu>{links(r, 5)}</div><div id=content><h1>⟦{few(r, 3)}⟧</h1><ol>{''.join(f'<li>⟦{r.choice([few(r, 3), prose(r, 8, 30)])}⟧</li>' for _ in range(6))}</ol>{paragraphs(r, 2)}</div><div id=footer><p>{prose(r, 8, 30)}</p></div></body>"


def comments_inside(r):
    return f"<article class=post><header><h1>⟦{few(r, 5)}⟧</h1></header>{paragraphs(r, 4)}<section class=comments>{''.join(f'<p>{prose(r, 20, 70)}</p>' for _ in range(r.randint(2, 7)))}</section></article><div class=newsletter><p>{prose(r, 15, 30)}</p><form><input><button>{few(r, 1)}</button></form></div>"


def divs(r):
    return f"<body><div><div>{few(r, 2)}</div><div>{links(r, 5)}</div></div><div class=wrapper>{paragraphs(r, 7, 'div')}</div><div class=widget><div>{prose(r, 10, 30)}</div></div><div class=copyright>{few(r, 4)}</div></body>"


def story(r):
    return f"<body><div class=banner><p>{prose(r, 10, 20)}</p></div><div class=story-body><p>⟦{prose(r, 20, 50)}⟧<p>⟦{few(r, 2)}⟧<p>⟦{prose(r, 30, 60)}⟧<p>⟦{few(r, 3)}⟧</div><div class=promo><p>{prose(r, 15, 40)}</p></div><div class=tags>{links(r, 3)}</div></body>"


def short_notes(r):
    return f"<body><ul class=breadcrumbs><li><a>{few(r, 1)}</a></li><li>{few(r, 1)}</li></ul><section><h2>⟦{few(r, 3)}⟧</h2>{''.join(f'<p>⟦{r.choice([few(r, 2), prose(r, 6, 14)])}⟧</p>' for _ in range(6))}<p>⟦{prose(r, 40, 80)}⟧</p></section><p>© {few(r, 3)}</p><p><a href=u>{few(r, 2)}</a></p></body>"


def old_page(r):
    return f"<html><body><center><b>{few(r, 2)}</b><br><a href=1>{few(r, 1)}</a> <a href=2>{few(r, 1)}</a></center><table><tr><td><a href=3>{few(r, 2)}</a><br><a href=4>{few(r, 2)}</a></td><td><p>⟦{prose(r, 30, 60)}⟧</p><p>⟦{few(r, 4)}⟧</p><p>⟦{prose(r, 30, 90)}⟧</p></td></tr></table></body></html>"


def captions(r: random.Random, n: int, tag: str = "div") -> str:
    """Short unlinked pieces such as menus of scripts, slogans and counters."""
    return "".join(f"<{tag}>{r.choice([few(r, r.randint(1, 3)), few(r, r.randint(2, 5)), str(r.randint(1, 999)), few(r, 2) + ':'])}</{tag}>" for _ in range(n))


def app_shell(r):
    """Names made by machine, menus without links."""
    return f"<body><div class=x1><div class=x2>{captions(r, 7)}</div><div class=x3>{captions(r, 3, 'span')}</div></div><div class=x4><div class=x5><h1>⟦{few(r, 4)}⟧</h1>{paragraphs(r, 8)}</div></div><div class=x6>{captions(r, 6, 'p')}</div><div class=x7><div>{captions(r, 4)}</div><div>{few(r, 6)}</div></div></body>"


def portal(r):
    return f"<body><header><h1>{few(r, r.randint(2, 6))}</h1></header><div><div>{captions(r, 4)}</div><table><tr>{captions(r, 5, 'td')}</tr></table></div><div><div>{paragraphs(r, 5)}<ul><li>⟦{few(r, 2)}⟧</li><li>⟦{few(r, 3)}⟧</li><li>⟦{prose(r, 10, 20)}⟧</li></ul>{paragraphs(r, 3)}</div><div>{captions(r, 5, 'p')}</div></div><div>{captions(r, 4, 'p')}</div></body>"


def interview(r):
    """Speakers' names and short answers as paragraphs of their own."""
    return f"<body><div>{captions(r, 5)}</div><article><h1>⟦{few(r, 4)}⟧</h1>{''.join(f'<p>⟦{few(r, 1)}⟧</p><p>⟦{r.choice([few(r, 2), prose(r, 6, 14), prose(r, 20, 50)])}⟧</p>' for _ in range(6))}</article><div>{captions(r, 4, 'p')}{links(r, 3)}</div><div>{captions(r, 2)}</div></body>"


def poem(r):
    return f"<body><ul>{captions(r, 6, 'li')}</ul><section><h2>⟦{few(r, 3)}⟧</h2><p>⟦{prose(r, 20, 40)}⟧</p>{''.join(f'<p>⟦{few(r, r.randint(3, 7))}⟧</p>' for _ in range(8))}<p>⟦{prose(r, 20, 40)}⟧</p></section><section>{captions(r, 5, 'p')}</section></body>"


SKELETONS = (app_shell, portal, interview, poem, article, blog, plain, bare_lines, news, manual, lists, comments_inside, divs, story, short_notes, old_page)


def clean(page: str) -> str:
    return page.replace("⟦", "").replace("⟧", "")


def labelled(page: str) -> list[tuple[html_extract.Block, bool]]:
    """The blocks of the page without marks, and whether each is marked."""
    marked, found = html_extract.blocks_of(page), html_extract.blocks_of(clean(page))
    assert [clean(b.text) for b in marked] == [b.text for b in found], page
    return [(b, m.text.startswith("⟦")) for b, m in zip(found, marked, strict=True)]


def pages(seeds: range, skeletons=SKELETONS) -> list[tuple[str, str]]:
    """(name of the skeleton, marked page)."""
    return [(f.__name__, f(random.Random(f"{f.__name__}{k}"))) for k in seeds for f in skeletons]
