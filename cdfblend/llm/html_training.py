"""Seeded labelled pages: varied site layouts with known content blocks, some with broken markup.

Names of classes and ids come in several languages, with decorations, at times invented, missing, or speaking of something
else (a story "worthy of comments"), so a model that learns from these pages has to weigh names against structure.
"""

from __future__ import annotations

import random

MARK = "data-truth"
_SYLLABLES = "an be co der el fi ga ho in ka lo mi na or pe ra si to un ver wa".split()


#: Names that site authors give to parts of a page, in several languages.
_NAMES = {
    "advert": "ad ads advert advertisement advertising banner sponsor sponsored promo promotion werbung anzeige anzeigen reklame publicite annonce publicidad anuncio anuncios pubblicita reclame",
    "menu": "menu nav navbar navigation breadcrumb breadcrumbs topnav hauptmenue navigationsleiste navegacion navigazione menuprincipal",
    "comment": "comment comments comment-list reply replies respond discussion disqus kommentar kommentare kommentarbereich diskussion antworten commentaire commentaires reponses comentario comentarios respuestas commenti reacties",
    "side": "sidebar side related related-posts recommended widget popular trending aside seitenleiste randspalte verwandte lateral barralateral relacionados laterale connexes correlati",
    "top": "header masthead topbar site-header banner-top kopfzeile seitenkopf entete cabecera encabezado intestazione",
    "bottom": "footer site-footer copyright colophon legal imprint fusszeile impressum pied pieddepage piedepagina pie",
    "notice": "notice cookie cookies cookie-notice consent gdpr newsletter subscribe popup alert paywall hinweis einwilligung zustimmung avis abonnement aviso boletin avviso",
    "share": "share sharing social social-links follow teilen partager compartir condividi",
    "form": "form search login signup contact suche anmeldung recherche connexion buscar busqueda ricerca",
    "content": "content article post entry story article-body post-content entry-content text prose main inhalt beitrag artikel haupttext contenu corps contenido articulo cuerpo contenuto testo",
}
_KINDS = list(_NAMES)


class _Writer:
    def __init__(self, rng: random.Random):
        self.r = rng

    def word(self) -> str:
        return "".join(self.r.choice(_SYLLABLES) for _ in range(self.r.randint(1, 4)))

    def words(self, lo: int, hi: int) -> str:
        return " ".join(self.word() for _ in range(self.r.randint(lo, hi)))

    def sentence(self) -> str:
        return self.words(3, 18).capitalize() + self.r.choice([".", ".", ".", "!", "?", ""])

    def prose(self, lo: int = 1, hi: int = 6) -> str:
        return " ".join(self.sentence() for _ in range(self.r.randint(lo, hi)))

    def link(self) -> str:
        return f'<a href="/{self.word()}">{self.words(1, 3)}</a>'

    def links(self) -> str:
        kind = self.r.random()
        items = [self.link() for _ in range(self.r.randint(2, 9))]
        if kind < 0.6:
            end = "</li>" if self.r.random() < 0.8 else ""
            return "<ul>" + "".join(f"<li>{x}{end}" for x in items) + "</ul>"
        return self.r.choice([" | ", " ", "<br>"]).join(items)

    def name(self, kind: str, invented: float) -> str:
        """A name for a part of some kind, at times invented or of two parts."""
        if self.r.random() < invented:
            return self.word() + self.r.choice(["", "-" + self.word()])
        name = self.r.choice(_NAMES[kind].split())
        how = self.r.random()
        if how < 0.15:
            return f"{name}-{self.r.choice(['box', 'wrap', 'area', 'inner', 'list', self.word()])}"
        if how < 0.25:
            return f"{self.word()}{name.capitalize()}"
        return f"{name} {self.word()}" if how < 0.35 else name

    def box(self, tag: str, kind: str, inner: str, truth: int = 0, plain: float = 0.1, invented: float = 0.06) -> str:
        """An element, plain or named by class, id or role; a story's name may speak of other kinds too."""
        attr = ""
        if kind and self.r.random() >= plain:
            name = self.name(kind, invented)
            if kind == "content" and self.r.random() < 0.15:
                other = self.r.choice(_NAMES[self.r.choice(_KINDS[:-1])].split())
                name = self.r.choice([f"{other}-{self.r.choice(['worthy', 'free', 'enabled', 'ready', self.word()])} {name}", f"{name} {self.r.choice(['has', 'with', 'no', self.word()])}-{other}"])
            attr = f' {self.r.choice(["class", "class", "id"])}="{name}"'
        return f'<{tag}{attr} {MARK}="{truth}">{inner}</{tag}>'

    def plain_or(self, tag: str, kind: str, inner: str) -> str:
        if self.r.random() < 0.5:
            return self.box(tag, kind, inner, plain=0.6, invented=0.2)
        return self.box(self.r.choice(["div", "div", "section"]), kind, inner, plain=0.0, invented=0.15 if "<a" in inner else 0.03)

    def junk(self) -> str:
        r = self.r.random()
        if r < 0.25:
            tag = self.r.choice(["div", "aside", "section", "p"])
            return self.box(tag, "advert", self.prose(1, 3) if tag == "p" else self.r.choice([self.prose(1, 3), f"<p>{self.prose(1, 2)}</p>", self.link()]))
        if r < 0.4:
            return self.plain_or("aside", "side", f"<h3>{self.words(1, 3)}</h3>" + self.r.choice([self.links(), f"<p>{self.prose(1, 3)}</p>"]))
        if r < 0.5:
            return self.box("div", "share", self.links(), plain=0.3, invented=0.3)
        if r < 0.65:
            if self.r.random() < 0.2:
                return self.box("p", "notice", self.prose(1, 2), plain=0.0, invented=0.0)
            return self.box(self.r.choice(["div", "div", "section", "aside"]), "notice", f"<p>{self.prose(1, 2)}</p>" + self.r.choice(["", f"<button>{self.words(1, 2)}</button>"]))
        if r < 0.8:
            inner = f"<label>{self.words(1, 3)}</label><input name=x><select><option>{self.word()}<option>{self.word()}</select><button>{self.words(1, 2)}</button>"
            return self.box("form", "form" if self.r.random() < 0.5 else "", self.r.choice([inner, f"<p>{self.prose(1, 2)}</p>{inner}"]))
        return self.plain_or("nav", "menu", self.links())

    def comments(self) -> str:
        one = lambda: self.box(self.r.choice(["div", "li", "article", "p"]), "comment", self.r.choice([self.prose(1, 3), f"<b>{self.word()}</b> {self.prose(1, 2)}", f"<p>{self.prose(1, 3)}</p>"]))
        inner = (f"<h2>{self.words(1, 2)}</h2>" if self.r.random() < 0.6 else "") + "".join(one() for _ in range(self.r.randint(1, 5)))
        return self.box(self.r.choice(["section", "div", "ol"]), "comment", inner, plain=0.05)

    def paragraph(self) -> str:
        if self.r.random() < 0.04:
            return f"<p>{self.link()}</p>"
        text = self.r.choice([self.prose(), self.prose(1, 1), f"{self.prose()} {self.link()} {self.sentence()}", f"<b>{self.sentence()}</b> {self.prose()}", f"<b>{self.sentence()}<br>"])
        return f"<p>{text}" + ("</p>" if self.r.random() < 0.8 else "")

    def body_block(self) -> str:
        r = self.r.random()
        if r < 0.72:
            return self.paragraph()
        if r < 0.8:
            return f"<h{(k := self.r.randint(2, 4))}>{self.words(1, 6)}</h{k}>"
        if r < 0.86:
            return "<ul>" + "".join(f"<li>{self.prose(1, 2)}</li>" for _ in range(self.r.randint(2, 5))) + "</ul>"
        if r < 0.9:
            return f"<blockquote>{self.r.choice([self.prose(), f'<p>{self.prose()}</p>'])}</blockquote>"
        if r < 0.93:
            return "<table>" + "".join("<tr>" + "".join(f"<td>{self.words(1, 4)}</td>" for _ in range(3)) + "</tr>" for _ in range(2)) + "</table>"
        if r < 0.96:
            return f"<pre>{self.words(2, 9)}\n  {self.words(2, 9)}</pre>"
        return f"<div>{self.prose()}</div>"

    def article(self) -> str:
        inner = [f"<h1>{self.words(2, 10)}</h1>"] if self.r.random() < 0.85 else []
        short = self.r.random() < 0.25
        if short and inner:
            inner.append(f"<p><b>{self.words(1, 6)}.<br>" if self.r.random() < 0.5 else f"<p>{self.words(1, 4)}.</p>")
        for _ in range(self.r.randint(0, 1) if short else self.r.randint(1, 14)):
            inner.append(f"<p>{self.words(1, 5)}.</p>" if short or self.r.random() < 0.08 else self.body_block())
            if self.r.random() < 0.06:
                inner.append(self.junk())
        if self.r.random() < 0.15:
            inner.append(self.comments())
        r = self.r.random()
        tag, kind = ("article", "") if r < 0.35 else ("main", "") if r < 0.45 else (self.r.choice(["article", "article", "main"]), "content") if r < 0.65 else (self.r.choice(["div", "section"]), "content")
        out = self.box(tag, kind, "".join(inner), 1, plain=0.08, invented=0.15)
        if self.r.random() < 0.3:
            out = self.box(self.r.choice(["main", "div"]), "content" if self.r.random() < 0.5 else "", out + (self.comments() if self.r.random() < 0.3 else ""), 0)
        return out

    def page(self) -> str:
        head = f"<!DOCTYPE html><html><head><title>{self.words(2, 6)}</title><style>p{{}}</style><script>var t='</p>';</script></head>"
        top = []
        if self.r.random() < 0.6:
            top.append(self.plain_or("header", "top", self.r.choice([f"<h1>{self.word()}</h1>", self.words(1, 3), f"<p>{self.words(1, 4)}</p>" + self.links()])))
        if self.r.random() < 0.8:
            top.append(self.plain_or("nav", "menu", self.links()))
        top += [self.junk() for _ in range(self.r.choice([0, 1, 1, 2]))]
        low = [self.junk() for _ in range(self.r.choice([0, 0, 1, 2]))]
        if self.r.random() < 0.3:
            low.append(self.comments())
        if self.r.random() < 0.85:
            low.append(self.plain_or("footer", "bottom", self.r.choice([f"&copy; {self.words(1, 6)}", f"<p>{self.prose(1, 3)}</p>", f"&copy; {self.prose(1, 3)}", self.links() + f"<p>{self.words(2, 8)}</p>"])))
        end = "</body></html>" if self.r.random() < 0.85 else ""
        if self.r.random() < 0.12:  # little but the article
            top, low = top[: self.r.randint(0, 1)], low[-self.r.randint(0, 1) :] if self.r.random() < 0.5 else []
        return f'{head}<body {MARK}="0">{"".join(top)}<!-- {self.word()} -->{self.article()}{"".join(low)}{end}'


def labelled_pages(n: int, seed: int) -> list[tuple[str, int]]:
    """``(html, index)``; blocks carry ``MARK`` = 1 for content, 0 for everything else, inherited inwards."""
    rng = random.Random(seed)
    return [(_Writer(rng).page(), k) for k in range(n)]
