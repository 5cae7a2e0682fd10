"""Generated web pages with known main text, to train the block labeller.

A page is drawn in one of several styles: by element (nav, article, footer), by
telling class names, by class names that say nothing, by tables, or with no names at
all. In the last three the labeller has only words, links, lengths and order to go by.
"""

from __future__ import annotations

import random

import numpy as np

#: Parts of invented words, and common words of a few languages, of which articles are made.
_SYLLABLES = "é è ü ß ción ñ ö ê an be ca de en fi ga he is jo ke la mi no or pe qua re si ti un ve wi ou th st er ion al".split()
_COMMON = (
    "the of and to in that was for with had from were this which when after more there would about been into only over year people first water time house new".split(),
    "der die und das nicht von sie ist des sich mit dem ein auch auf für als wird aus nach bei einer noch war haben nur über vor zwei jahr".split(),
    "le la de et les des que une est dans pour pas sur qui par plus avec il ce sont mais nous aux deux leur été fait ans où".split(),
    "el la de que y en los se del las un por con no una su para es al lo como más pero sus este ha entre cuando muy".split(),
    "он она это как так был для что все его при уже или они был год дом вода время".split(),
    "的 是 在 了 人 有 我 他 这 中 大 来 上 国 和 地 到 说 时 要".split(),
)

#: Names that authors give to the parts of a page.
MENU = "nav menu navbar navigation topnav sitenav breadcrumb breadcrumbs mainmenu submenu toolbar pagination pager tabs skip".split()
HEADER = "header masthead banner top logo branding siteheader hero topbar".split()
FOOTER = "footer copyright colophon legal bottom sitefooter credits imprint".split()
SIDE = "sidebar aside rail side widget widgets related recommended popular trending archive tags tagcloud toc".split()
NOTICE = "notice cookie cookies consent gdpr alert popup modal overlay subscribe newsletter paywall message".split()
ADVERT = "ad ads advert advertisement adslot sponsor sponsored promo promotion banner outbrain taboola".split()
FORM = "form search searchform login signup contact subscribe feedback".split()
COMMENT = "comment comments commentlist discussion reply replies responses disqus respond thread reader".split()
SHARE = "share social sharing follow byline meta author".split()
MAIN = "content main article post entry story body text page maincontent articlebody postcontent".split()

#: What surroundings say, in a few languages.
SAYS = {
    "menu": "Home|News|Sport|About us|Contact|Products|Blog|Archive|Shop|Login|Help|Business|Culture|Travel|Weather|Video|Startseite|Über uns|Kontakt|Nachrichten|Accueil|À propos|Actualités|Inicio|Noticias|Contacto|Sign in|My account|Next|Previous|Menu|Skip to content|Politics|Opinion|Science".split("|"),
    "footer": "All rights reserved|Privacy policy|Terms of use|Terms and conditions|Imprint|Copyright|Contact us|Powered by|Alle Rechte vorbehalten|Impressum|Datenschutz|Tous droits réservés|Mentions légales|Todos los derechos reservados|Aviso legal|Follow us on social media|Accessibility|Sitemap|Cookie settings|Registered office|Made with care by the team".split("|"),
    "notice": "We use cookies to improve your experience on this website.|By continuing to browse you agree to our use of cookies.|Accept all cookies|Manage preferences|Subscribe to our newsletter and get the latest stories in your inbox.|Sign up now|Your subscription has expired.|Please enable JavaScript to view this page.|Diese Website verwendet Cookies.|Alle akzeptieren|Ce site utilise des cookies pour vous offrir le meilleur service.|Tout accepter|Este sitio utiliza cookies propias y de terceros.|Aceptar|Enter your email address to continue.|You have read all your free articles this month.|Download our app|Never miss a story".split("|"),
    "advert": "Advertisement|Sponsored|Anzeige|Publicité|Publicidad|Buy now and save 50 percent|Limited offer: order today with free shipping.|Shop the sale|Ad|Promoted content|Best deals of the week|Click here to learn more|Get your free quote today|Try it free for 30 days, cancel anytime.|Paid content from our partner".split("|"),
    "side": "Related articles|Most read|Popular posts|Recent posts|Read more|You may also like|Trending now|Tags|Categories|More from this author|Recommended for you|Mehr zum Thema|Das könnte Sie auch interessieren|À lire aussi|Les plus lus|Lo más leído|Archives|In this section|Editor's picks|See also".split("|"),
    "form": "Search|Email|Password|Name|Your message|Submit|Send|Remember me|Forgot your password?|Subscribe|Suche|Senden|Rechercher|Envoyer|Buscar|Enviar|Required fields are marked|I agree to the terms|Select your country".split("|"),
    "comment": "Reply|Leave a comment|comments|says:|Report|Log in to comment|Like|Antworten|Kommentare|Répondre|Commentaires|Responder|Comentarios|Thanks for this article!|I totally agree with you.|Great post, thank you.|First!|This is wrong, in my opinion.|2 hours ago|3 days ago|Posted by|wrote:|Flag as inappropriate|lol".split("|"),
    "share": "Share|Tweet|Share on Facebook|Email this|Print|By|Published|Updated|min read|Follow|Copy link|Teilen|Partager|Compartir|Posted on|Staff writer|Photo:|Last modified".split("|"),
}
#: Words of those phrases; articles use them as well, so that no word tells by itself.
_SAID = sorted({w.strip(".,:!?").lower() for phrases in SAYS.values() for p in phrases for w in p.split()} - {""})
STYLES = ("elements", "elements", "names", "names", "hashed", "bare", "tables")


def make_page(rng: np.random.Generator) -> list[tuple[str, bool]]:
    """Pieces of a page in order; True marks pieces whose text is main text."""
    out: list[tuple[str, bool]] = []
    draw = random.Random(int(rng.integers(1 << 62)))
    unit = draw.random
    pick = lambda x: x[int(unit() * len(x))]
    within = lambda a, b=0: min(a, b) + int(unit() * abs(b - a))
    chance = lambda p: unit() < p

    style = pick(STYLES)
    telling = style in ("elements", "names")
    common, invented, borrowed = pick(_COMMON), draw.random(), 0.4 * draw.random()
    #: Marks that odd texts carry at their words, whatever part of the page they are in.
    mark = "".join(pick("#$%*!|+~@=^") for _ in range(within(1, 4))) if chance(0.08) else ""
    longest = pick([3, 4, 6, 10, 24])

    def word() -> str:
        w = pick(_SAID) if chance(borrowed) else pick(common) if not chance(invented) else "".join(pick(_SYLLABLES) for _ in range(within(1, 5)))
        return w + mark if mark and chance(0.8) else w

    def sentence(low: int = 4, high: int = 18) -> str:
        s = " ".join(word() for _ in range(within(low, high)))
        if chance(0.15):
            s = s.replace(" ", ", ", 1)
        return s[:1].upper() + s[1:] + pick([".", ".", ".", ".", "?", "!", ""])

    def prose(low: int = 1, high: int = 6) -> str:
        return " ".join(sentence() for _ in range(within(low, high)))

    def short() -> str:
        return " ".join(word() for _ in range(within(1, 5))) + pick(["", "", "", "."])

    def says(kind: str, odds: float = 0.0) -> str:
        """A stock phrase; on pages whose names tell the part, at times any words."""
        if telling and chance(0.5 + odds):
            return short() if chance(0.5) else prose(1, 3)
        return pick(SAYS[kind])

    def names(kind: list[str]) -> str:
        if style == "hashed":
            return f'class="{pick(["css", "sc", "x", "jss", "c"])}-{within(1 << 24):x}"'
        if not telling:
            return ""
        form = within(5)
        name = pick(kind)
        if form == 0:
            name = f"{name}-{pick(['inner', 'box', 'wrap', 'block', 'area', 'list', 'item'])}"
        elif form == 1:
            name = f"{pick(['site', 'page', 'global', 'main', 'top'])}-{name}" if kind is not MAIN else name
        return f'{pick(["class", "class", "id"])}="{name}"'

    def put(piece: str, main: bool = False) -> None:
        out.append((piece, main))

    def shell(kind: list[str], tags: list[str], inner) -> None:
        tag = pick(tags) if style != "names" or chance(0.3) else "div"
        if not telling and tag not in ("ul", "ol", "p", "span", "table") and chance(0.8):
            tag = "div"
        label = names(kind) if tag in ("div", "section", "ul", "ol", "span", "p", "ins") or chance(0.4) else ""
        put(f"<{tag}{' ' + label if label else ''}>")
        inner()
        put(f"</{tag}>")

    def links(kind: str = "menu") -> None:
        form = pick(["list", "list", "list", "row", "cells", "divs"])
        n = within(2, 10)
        put({"list": "<ul>", "row": "<div>", "cells": "<table><tr>", "divs": "<div>"}[form])
        for _ in range(n):
            a = f'<a href="/{within(999)}">{says(kind, 0.2) if not chance(0.3) else sentence(3, 9)}</a>'
            put({"list": f"<li>{a}</li>", "row": a + pick([" ", " | ", " &middot; "]), "cells": f"<td>{a}</td>", "divs": f"<div>{a}</div>"}[form])
        put({"list": "</ul>", "row": "</div>", "cells": "</tr></table>", "divs": "</div>"}[form])

    def plain(kind: str):
        def inner() -> None:
            for _ in range(within(1, 4)):
                text = says(kind)
                put(pick([f"<p>{text}</p>", text, f"<span>{text}</span>", f"<div>{text}</div>", f'<a href="/">{text}</a>']))

        return inner

    def heading_links() -> None:
        n = within(2, 5)
        put(f"<h{n}>{says('side')}</h{n}>")
        links("side")

    def form() -> None:
        put(f'<form action="/{within(99)}"><label>{says("form", 0.2)}</label><input type="text" name="q">')
        if chance(0.4):
            put(f"<select><option>{short()}</option><option>{short()}</option></select>")
        put(f"<p>{says('form')}</p>" if chance(0.3) else "")
        put(f"<button>{says('form', 0.2)}</button></form>")

    def comments() -> None:
        put(f"<h3>{says('comment')}</h3>" if chance(0.7) or not telling else "")
        item = pick(["li", "div", "article", "p"]) if telling else pick(["li", "div"])
        inner = names(COMMENT)
        for _ in range(within(1, 7)):
            put(f"<{item} {inner if item == 'article' or chance(0.8) else ''}>")
            who = short() if telling else f"{short()} {pick(SAYS['comment'])}"
            put(f"<b>{who}</b> " if chance(0.5) else f"<cite>{who}</cite>" if chance(0.4) or not telling else "")
            put(f"<p>{prose(1, 4)}</p>" if item != "p" else prose(1, 4))
            put(f'<a href="#">{pick(SAYS["comment"])}</a>' if chance(0.5) else "")
            put(f"</{item}>")
        if chance(0.3):
            form()

    def footer() -> None:
        if chance(0.5):
            links("footer")
        mine = f"{pick(['&copy;', '©', 'Copyright', '(c)'])} {within(1999, 2030)} {short()}"
        put(pick([f"&copy; site.example.com &middot; {sentence() if telling else pick(SAYS['footer'])}", f"<p>{mine}</p>", f"<p>{mine}. {pick(SAYS['footer'])}.</p>", f"<small>{says('footer')}</small>", says("footer")]))

    advert = lambda: shell(ADVERT, ["div", "div", "aside", "ins", "section"], plain("advert"))
    notice = lambda: shell(NOTICE, ["div", "div", "section", "aside", "p"], plain("notice"))
    share = lambda: shell(SHARE, ["div", "ul", "p"], lambda: put(pick([f"<a href='#'>{says('share')}</a> {says('share')}", f"<span>{pick(['By', 'Von', 'Par', 'Por'])} {short()}</span>", f"{within(1, 31)} {pick('January May Juni octobre marzo December'.split())} {within(1999, 2030)}"])))
    side = lambda: shell(SIDE, ["aside", "div", "section"], pick([heading_links, plain("side"), lambda: links("side")]))

    def paragraph(text: str, block: str) -> None:
        if block == "p":
            odd = chance(0.15)
            put(f"<p>{'<b>' if odd else ''}{text}{'<br>' if odd else ''}{'' if odd or chance(0.1) else '</p>'}", True)
        elif block == "div":
            label = names(MAIN) if style == "hashed" or chance(0.2) else ""
            put(f"<div{' ' + label if label else ''}>{text}</div>", True)
        else:
            put(f"{text}<br><br>", True)

    def article() -> None:
        if telling:
            tags = [("article", None), ("main", None), ("div", MAIN), ("section", MAIN), ("article", MAIN), ("td", None), ("div", None)]
        else:
            tags = [("td", None)] if style == "tables" else [("div", MAIN), ("div", MAIN), ("main", None), ("section", None)]
        chain = [pick(tags) for _ in range(within(1, 3))]
        for tag, kind in chain:
            label = names(kind) if kind else ""
            put("<table><tr><td>" if tag == "td" else f"<{tag}{' ' + label if label else ''}>")
        block = pick(["p"] * 6 + ["div"]) if telling else pick(["p", "p", "div", "br"])
        if chance(0.8):
            put("<header>" if (inside := chance(0.15)) else "")
            n = 1 if chance(0.8) else 2
            put(f"<h{n}>{sentence(2, 12)}</h{n}>", True)
            put("</header>" if inside else "")
        if chance(0.3):
            share()
        for _ in range(within(1 if telling else 2, 16)):
            kind = draw.random()
            if kind < 0.66:
                text = prose(1 if telling or chance(0.3) else 2, longest) if chance(0.85) else sentence(2, 8)
                if chance(0.2):
                    text = text.replace(" ", f' <a href="/{within(99)}">{short()}</a> ', 1)
                paragraph(text, block)
            elif kind < 0.76:
                n = within(2, 5)
                put(f"<h{n}>{sentence(1, 6)}</h{n}>", True)
            elif kind < 0.82:
                put(pick(["<ul>", "<ol>"]))
                for _ in range(within(2, 6)):
                    put(f"<li>{sentence(2, 12)}</li>", True)
                put("</ul></ol>")
            elif kind < 0.85:
                put(f"<blockquote><p>{prose(1, 3)}</p></blockquote>", True)
            elif kind < 0.87:
                put(f"<pre>{prose(1, 3)}</pre>", True)
            elif kind < 0.88:
                put(f"<figure><img src='/{within(99)}.jpg'><figcaption>{sentence()}</figcaption></figure>", True)
            elif kind < 0.90:
                put("<table>")
                for _ in range(within(1, 4)):
                    put(f"<tr><td>{short()}</td><td>{sentence(1, 6)}</td></tr>", True)
                put("</table>")
            elif kind < 0.92:
                put(f"<div>{prose(1, 4)}</div>", True)
            elif kind < 0.95:
                advert()
            elif kind < 0.98:
                side()
            else:
                notice()
        if chance(0.15):
            share()
        if chance(0.12):
            shell(COMMENT, ["section", "div"], comments)
        for tag, _ in reversed(chain):
            put("</td></tr></table>" if tag == "td" else f"</{tag}>")

    put(f'<!DOCTYPE html><html lang="en"><head><meta charset="utf-8"><title>{sentence(1, 9)}</title><style>p{{margin:0}}</style></head><body>')
    wrapped = chance(0.4)
    label = names(["wrapper", "container", "page", "site", "layout", "root", "app"])
    put(f"<div{' ' + label if label else ''}>" if wrapped else "")
    columns = style == "tables" and chance(0.7)
    before = [lambda: shell(MENU, ["nav", "nav", "div", "ul"], links), lambda: shell(HEADER, ["header", "header", "div"], pick([links, plain("menu"), lambda: put(f"<h1>{short()}</h1><p>{sentence() if telling else pick(SAYS['menu'])}</p>" if telling else f"<div>{short()}</div>"), form])), advert, notice, side, lambda: shell(FORM, ["div", "section"], form), form]
    after = [lambda: shell(COMMENT, ["section", "div", "ol", "ul"], comments), side, advert, notice, lambda: shell(FORM, ["div", "section"], form), share, lambda: shell(MENU, ["nav", "div"], links)]
    put("<table><tr><td>" if columns else "")
    for part in before:
        if chance(0.42):
            part()
    put("</td><td>" if columns else "")
    if chance(0.97):
        article()
    put("</td><td>" if columns else "")
    for part in after:
        if chance(0.4):
            part()
    put("</td></tr></table>" if columns else "")
    if chance(0.85):
        shell(FOOTER, ["footer", "footer", "div"], footer)
    put("</div>" if wrapped else "")
    put("</body></html>" if chance(0.9) else "")
    return out
