"""Stage 2: text with LaTeX from HTML, one parse a page.

Order: equations are found and replaced by placeholders in the tree; invisible and blocked elements, buttons and
link clusters go; the main content is chosen; lines are rendered; placeholders become normalised LaTeX. Only
equations whose placeholder is still there at the end count.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from html import unescape
from html.parser import HTMLParser
from urllib.parse import unquote_plus

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import lexicon as L
from ..functions import columns as C
from . import lines
from .mathml import convert

VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
BLOCKS = {"address", "article", "aside", "blockquote", "body", "dd", "details", "div", "dl", "dt", "fieldset", "figure", "footer", "form", "h1", "h2", "h3", "h4", "h5", "h6", "header", "hr", "html", "li", "main", "nav", "ol", "p", "pre", "section", "table", "tbody", "td", "tfoot", "th", "thead", "tr", "ul"}
CLOSES_P = BLOCKS - {"html", "body", "td", "th", "tr", "tbody", "thead", "tfoot"}
DROPPED = {"script", "style", "noscript", "template", "head", "title", "svg", "iframe"}
PRIOR = {"article": 3.0, "main": 3.0, "section": 1.2, "div": 1.0, "body": 0.6, "td": 0.8, "nav": 0.05, "footer": 0.05, "aside": 0.2, "header": 0.4, "form": 0.2}
MARK = "\ue000{}\ue001"
_MARKED = re.compile("\ue000(\\d+)\ue001")


@dataclass
class Node:
    tag: str
    attrs: dict = field(default_factory=dict)
    children: list = field(default_factory=list)
    parent: "Node | None" = None

    def text(self) -> str:
        out, stack = [], [self]
        while stack:
            n = stack.pop()
            if isinstance(n, str):
                out.append(n)
            else:
                stack.extend(reversed(n.children))
        return "".join(out)

    def walk(self) -> Iterator["Node"]:
        stack = [self]
        while stack:
            n = stack.pop()
            yield n
            stack.extend(c for c in reversed(n.children) if not isinstance(c, str))

    def classes(self) -> list[str]:
        return (self.attrs.get("class") or "").split()


class _Builder(HTMLParser):
    """Tolerant: unclosed elements end with their parents, paragraphs end before blocks, scripts are raw text."""

    CDATA_CONTENT_ELEMENTS = ("script", "style")

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.root = Node("document")
        self.at = self.root
        self.depth = 0

    def _open(self, tag: str, attrs) -> Node:
        n = Node(tag, {k: v if v is not None else "" for k, v in attrs}, [], self.at)
        self.at.children.append(n)
        return n

    def handle_starttag(self, tag, attrs):
        if tag in CLOSES_P:
            self._close("p", BLOCKS - {"p"})
        elif tag == "li":
            self._close("li", {"ul", "ol"})
        n = self._open(tag, attrs)
        if tag not in VOID and self.depth < 400:
            self.at = n
            self.depth += 1

    def handle_startendtag(self, tag, attrs):
        self._open(tag, attrs)

    def _close(self, tag: str, stop: set[str]) -> None:
        n = self.at
        while n is not None and n.tag != tag:
            if n.tag in stop or n is self.root:
                return
            n = n.parent
        if n is not None and n.parent is not None:
            while self.at is not n:
                self.at, self.depth = self.at.parent, self.depth - 1
            self.at, self.depth = n.parent, self.depth - 1

    def handle_endtag(self, tag):
        self._close(tag, set())

    def handle_data(self, data):
        self.at.children.append(data)


def parse(html: str) -> Node:
    b = _Builder()
    b.feed(html)
    b.close()
    return b.root


# ---- equations


@dataclass
class Equation:
    latex: str
    encoding: str
    display: bool


def configured_delimiters(html: str) -> list[tuple[str, str, bool]]:
    """Delimiter pairs that a page's renderer configuration sets: inlineMath and displayMath lists, JavaScript escapes undone."""
    out, quoted = [], r"""(?:'((?:\\.|[^'\\])+)'|"((?:\\.|[^"\\])+)")"""
    undo = lambda x: re.sub(r"\\(.)", r"\1", x)
    for key, display in (("inlineMath", False), ("displayMath", True)):
        # version 2 and 3 give a list of pairs, later ones also an object that adds to the defaults
        for body in re.findall(rf"""{key}["']?\s*:\s*(?:\{{\s*["']\[\+\]["']\s*:\s*)?\[((?:\s*\[[^\[\]]*(?:\\\[|\\\]|[^\[\]])*?\]\s*,?)+)\s*\]""", html):
            out += [(undo(a or b), undo(c or d), display) for a, b, c, d in re.findall(rf"\[\s*{quoted}\s*,\s*{quoted}\s*\]", body)]
    return [(a, b, d) for a, b, d in out if a and b]


DELIMITERS = (("$$", "$$", True), (r"\[", r"\]", True), (r"\(", r"\)", False), ("[tex]", "[/tex]", True), ("[math]", "[/math]", True), ("[itex]", "[/itex]", False), ("$latex ", "$", False), ("$", "$", False))
_ENVIRONMENT = re.compile(r"\\begin\{(align|equation|gather|multline|eqnarray)(\*?)\}")
_COMMAND = re.compile(L.COMMAND_PATTERN)
_COMMON = {"\\" + c for c in L.COMMANDS}


def has_common_command(text: str) -> bool:
    return any(c in _COMMON for c in _COMMAND.findall(text))


def dollars_are_math(html: str, text: str, policy: str, score=None) -> bool:
    """script: the renderer's word is there; command: a common command stands between dollars; score: a scorer says so; cascade: any."""
    checks = {
        "script": lambda: "MathJax" in html or "mathjax" in html or "katex" in html,
        "command": lambda: any(has_common_command(s) for s in re.findall(r"(?=\$([^$]+)\$)", text)),  # spans between any two neighbouring dollars
        "score": lambda: score is not None and score(text) > L.PREFILTER_CUT,
    }
    return any(checks[p]() for p in (("script", "command", "score") if policy == "cascade" else (policy,)))


def is_price(body: str) -> bool:
    """What stands between a price's dollar and the next one: a number, prose without a command, and a blank at the end."""
    return bool(re.match(r"\d[\d.,]*\s", body)) and body[-1].isspace() and not has_common_command(body)


def scan(text: str, delimiters, dollars: bool) -> list[tuple[int, int, Equation]]:
    """Delimited equations and environments from left to right: longest opener first, display before inline, an escaped
    dollar opens nothing, a single dollar doesn't cross a blank line, unbalanced openers are text."""
    pairs = sorted(delimiters, key=lambda p: (-len(p[0]), not p[2]))
    openers = re.compile("|".join([r"\\\$", r"\${3,}", _ENVIRONMENT.pattern, *(re.escape(a) for a, _, _ in pairs)]))
    by = {a: (b, d) for a, b, d in reversed(pairs)}
    out, at = [], 0
    while m := openers.search(text, at):
        opener, at = m.group(), m.end()
        if opener == r"\$" or opener.startswith("$$$"):  # escaped, or a run that delimits nothing
            continue
        env = _ENVIRONMENT.match(opener)
        if env:
            end = rf"\end{{{env[1]}{env[2]}}}"
            stop = text.find(end, at)
            if stop >= 0:
                out.append((m.start(), stop + len(end), Equation(text[m.start() : stop + len(end)], env[1] if env[1] in ("align", "equation") else "align", True)))
                at = stop + len(end)
            continue
        if opener in ("$", "$$") and not dollars:
            continue
        close, display = by[opener]
        if close.startswith("$"):
            end_of = re.compile(rf"(?<![\\$]){re.escape(close)}(?!\$)").search(text, at)
            stop = end_of.start() if end_of else -1
        else:
            stop = text.find(close, at)
        body = text[at:stop] if stop >= 0 else ""
        if stop < 0 or not body.strip() or (opener == "$" and ("\n\n" in body or is_price(body))):
            continue
        default = (opener, close, display) in DELIMITERS
        kind = "plugin" if opener == "$latex " else ("display" if display else "inline") if default else "configured"
        out.append((m.start(), stop + len(close), Equation(body.strip(), kind, display)))
        at = stop + len(close)
    return out


_CODECOGS = re.compile(r"(?:codecogs\.com|/mathtex|/mimetex|tex\.cgi)[^?]*\?(.+)", re.S)
_PLUGIN = re.compile(r"latex\.php\?(?:[^&]*&)*latex=([^&]+)", re.S)


def _element_equation(n: Node) -> Equation | None:
    if n.tag == "script" and (n.attrs.get("type") or "").startswith("math/"):
        return Equation(n.text().strip(), "script", "mode=display" in n.attrs["type"])
    if n.tag == "math":
        note = next((c for c in n.walk() if c.tag == "annotation" and c.attrs.get("encoding") == "application/x-tex"), None)
        display = n.attrs.get("display") == "block"
        if note is not None:
            return Equation(note.text().strip(), "annotation", display)
        if n.attrs.get("alttext"):
            return Equation(n.attrs["alttext"].strip(), "alttext", display)
        return Equation(convert(n).strip(), "mathml", display)
    if n.tag == "mathjax":
        return Equation(n.text().strip(), "tag", False)
    if n.tag == "img":
        src = unescape(n.attrs.get("src") or "")
        if m := _PLUGIN.search(src):
            return Equation(unquote_plus(m[1]).strip(), "plugin", False)
        if m := _CODECOGS.search(src):
            return Equation(unquote_plus(m[1]).strip(), "image", False)
        alt = n.attrs.get("alt") or ""
        if has_common_command(alt) or ({"latex", "tex"} & set(n.classes()) and alt):
            return Equation(alt.strip().strip("$"), "image", False)
    if "math-container" in n.classes():
        return Equation(n.text().strip().strip("$"), "container", False)
    if "tex" in n.classes():
        return Equation((n.attrs.get("alttext") or n.text()).strip().strip("$"), "alttext", False)
    return None


def mark_equations(root: Node, html: str, policy: str = "cascade", score=None) -> list[Equation]:
    """Replace every encoded equation of the tree by a placeholder."""
    found: list[Equation] = []

    def put(eq: Equation) -> str:
        found.append(eq)
        return MARK.format(len(found) - 1)

    visible = []

    def elements(n: Node) -> None:
        for i, c in enumerate(n.children):
            if isinstance(c, str):
                if n.tag not in DROPPED and n.tag not in ("code", "pre", "textarea"):
                    visible.append(c)
            elif (eq := _element_equation(c)) is not None and eq.latex:
                n.children[i] = put(eq)
            else:
                elements(c)

    elements(root)
    pairs = [*DELIMITERS, *configured_delimiters(html)]
    dollars = dollars_are_math(html, "\n".join(visible), policy, score)

    def texts(n: Node) -> None:
        if n.tag in DROPPED or n.tag in ("code", "pre", "textarea"):
            return
        for i, c in enumerate(n.children):
            if not isinstance(c, str):
                texts(c)
            elif spans := scan(c, pairs, dollars):
                parts, at = [], 0
                for a, b, eq in spans:
                    parts += [c[at:a], put(eq)]
                    at = b
                n.children[i] = "".join([*parts, c[at:]])

    texts(root)
    return found


# ---- tree


_HIDDEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)


def _is_button(n: Node) -> bool:
    return n.tag == "button" or n.attrs.get("role") == "button" or (n.tag == "input" and n.attrs.get("type") in ("button", "submit", "reset"))


def link_share(n: Node) -> tuple[int, int, int]:
    """(links, characters in links, characters)."""
    links = [c for c in n.walk() if c.tag == "a"]
    return len(links), sum(len(a.text().strip()) for a in links), len(n.text().strip())


def clean(root: Node, blocked=L.BLOCKED, min_links: int = 4, min_share: float = 0.6, hidden=True, buttons=True, clusters=True) -> Node:
    """Remove invisible elements, scripts, buttons, blocked classes and ids, and link clusters."""
    bad = set(blocked)

    def goes(n: Node) -> bool:
        if n.tag in DROPPED:
            return True
        if hidden and ("hidden" in n.attrs or _HIDDEN.search(n.attrs.get("style") or "")):
            return True
        if buttons and _is_button(n):
            return True
        if n.attrs.get("id") in bad or bad & set(n.classes()) or n.tag in bad:
            return True
        if clusters and n.tag in BLOCKS and n.tag not in ("body", "html", "article", "main"):
            k, inside, total = link_share(n)
            return k >= min_links and total > 0 and inside >= min_share * total
        return False

    def prune(n: Node) -> None:
        n.children = [c for c in n.children if isinstance(c, str) or not goes(c)]
        for c in n.children:
            if not isinstance(c, str):
                prune(c)

    prune(root)
    return root


def main_content(root: Node) -> Node:
    """The element with the best score: own text outside links, times a prior of its tag; equations weigh extra, so a
    block with one is never the reason to choose another. Falls back to the body."""
    body = next((n for n in root.walk() if n.tag == "body"), root)
    best, top = body, -1.0

    def measure(n: Node) -> float:
        nonlocal best, top
        own = 0.0
        for c in n.children:
            if isinstance(c, str):
                own += len(c.strip()) + 40 * len(_MARKED.findall(c))
            else:
                inner = measure(c)
                own += 0 if c.tag in ("nav", "footer", "aside") else inner * (0.2 if c.tag == "a" else 1.0)
        if n.tag in PRIOR and n.tag not in ("nav", "footer"):
            score = own * PRIOR[n.tag]
            if score > top:
                best, top = n, score
        return own

    measure(body)
    return best


def render(n: Node, markdown: bool) -> str:
    """Lines of text: blocks end lines, headers, code, tables and lists are marked in Markdown."""
    out: list[str] = []

    def go(n: Node, pre: bool) -> None:
        block = n.tag in BLOCKS
        if block:
            out.append("\n")
        if n.tag[:1] == "h" and n.tag[1:].isdigit() and markdown:
            out.append("#" * int(n.tag[1:]) + " ")
        elif n.tag == "li":
            out.append("- " if markdown else "")
        elif n.tag == "pre" and markdown:
            out.append("```\n")
        elif n.tag == "code" and markdown and not pre:
            out.append("`")
        elif n.tag == "br":
            out.append("\n")
        elif n.tag in ("td", "th"):
            out.append(" | " if markdown else " ")
        for c in n.children:
            if isinstance(c, str):
                out.append(c if pre or n.tag == "pre" else re.sub(r"[ \t\r\f\v]+", " ", c))
            else:
                go(c, pre or n.tag == "pre")
        if n.tag == "code" and markdown and not pre:
            out.append("`")
        elif n.tag == "pre" and markdown:
            out.append("\n```")
        if block:
            out.append("\n")

    go(n, False)
    rows = [r.strip() for r in "".join(out).split("\n")]
    return "\n".join(r for i, r in enumerate(rows) if r or (i and rows[i - 1]))


def strip_repeated_header(text: str) -> str:
    """Without a first line that the next one starts with."""
    rows = text.split("\n")
    full = [i for i, r in enumerate(rows) if r]
    if len(full) > 1 and rows[full[1]].startswith(rows[full[0]].lstrip("# ").rstrip(".")):
        return "\n".join(rows[full[1] :])
    return text


@dataclass
class Page:
    text: str | None
    equations: list[Equation]
    status: str


def extract(html: str | None, markdown: bool = False, policy: str = "cascade", score=None, main: bool = True, blocked=L.BLOCKED) -> Page:
    """Text and equations of a page; status ok, empty or parse_error, never an exception. Pages of any length are read whole."""
    if not html:
        return Page(None, [], "empty")
    try:
        root = parse(html)
        found = mark_equations(root, html, policy, score)
        clean(root, blocked)
        text = render(main_content(root) if main else root, markdown)
        text = strip_repeated_header(text.strip())
        kept = [found[int(i)] for i in _MARKED.findall(text)]
        text = text.replace("$", r"\$")
        text = _MARKED.sub(lambda m: (f"$${found[int(m[1])].latex}$$" if found[int(m[1])].display else f"${found[int(m[1])].latex}$"), text)
        return Page(text, kept, "ok")
    except (ValueError, RecursionError, AssertionError) as e:
        return Page(None, [], f"parse_error: {type(e).__name__}")


EXTRACTED = "page_id long, url string, text string, equations array<struct<ord: int, latex: string, encoding: string, display: boolean>>, has_latex boolean, output_format string, boilerplate_trigger int, status string"


def pages(df: DataFrame, seed: int = 7, policy: str = "cascade", markdown_share: float = 0.5, trigger: tuple[int, int] = (1, 3)) -> DataFrame:
    """page_id, url, html -> documents. Parameters are drawn per page in the JVM; the line stage runs in the JVM after.
    A column math_score decides the last step of the dollar cascade; without it the score of the word list does."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            rows = []
            for r in f.itertuples(index=False):
                p = extract(r.html, r.output_format == "markdown", policy, lambda _, s=r.math_score: s if s == s and s is not None else 0.0)
                rows.append((r.page_id, r.url, p.text, [{"ord": i, "latex": e.latex, "encoding": e.encoding, "display": e.display} for i, e in enumerate(p.equations)], bool(p.equations), r.output_format, r.boilerplate_trigger, p.status))
            yield pd.DataFrame(rows, columns=[c.split()[0] for c in ("page_id", "url", "text", "equations", "has_latex", "output_format", "boilerplate_trigger", "status")])

    score = F.col("math_score") if "math_score" in df.columns else C.lexicon_score(C.quick_text(F.col("html")))
    ready = df.select("page_id", "url", "html", score.cast("double").alias("math_score"), *lines.parameters(F.col("page_id"), seed, markdown_share, *trigger))
    raw = ready.mapInPandas(run, EXTRACTED)
    return raw.withColumn("text", lines.drop_empty_headers(lines.drop_boilerplate(F.col("text"), F.col("boilerplate_trigger"))))


# ---- baselines: families of extractors


def plain_strip(html: str) -> str:
    return re.sub(r"\s+", " ", unescape(re.sub("<[^>]*>", " ", re.sub(r"(?s)<script.*?</script>|<style.*?</style>|<!--.*?-->", " ", html)))).strip()


def article_only(html: str) -> str:
    m = re.search(r"(?s)<article[^>]*>(.*?)(?:</article>|$)", html)
    return plain_strip(m[1] if m else html)


def _blocks(html: str) -> list[Node]:
    root = clean(parse(html), blocked=(), clusters=False)
    return [n for n in root.walk() if n.tag in ("p", "li", "td", "pre", "blockquote", "h1", "h2", "h3")]


def stop_word_paragraphs(html: str) -> str:
    """Paragraphs that are long, have few links and enough stop words of any language."""
    stops = {w for words in L.STOP_WORDS.values() for w in words}
    out = []
    for n in _blocks(html):
        text = n.text().strip()
        words = text.lower().split()
        k, inside, total = link_share(n)
        if len(text) >= 70 and inside <= 0.2 * total and sum(w in stops for w in words) >= 0.1 * len(words):
            out.append(text)
    return "\n".join(out)


def largest_block(html: str) -> str:
    root = clean(parse(html), blocked=(), clusters=False)
    nodes = [n for n in root.walk() if n.tag in ("article", "div", "section", "td", "main")] or [root]
    return max(nodes, key=lambda n: sum(len(c.text()) for c in n.children if not isinstance(c, str) and c.tag == "p") + sum(len(c) for c in n.children if isinstance(c, str))).text().strip()


def low_link_density(html: str) -> str:
    return "\n".join(n.text().strip() for n in _blocks(html) if (lambda s: s[2] and s[1] <= 0.33 * s[2])(link_share(n)))


def to_markdown(html: str) -> str:
    return render(clean(parse(html), blocked=(), clusters=False), True)


EXTRACTORS = {"plain_strip": plain_strip, "article_only": article_only, "stop_word_paragraphs": stop_word_paragraphs, "largest_block": largest_block, "low_link_density": low_link_density, "to_markdown": to_markdown, "ours": lambda h: extract(h).text or "", "ours_markdown": lambda h: extract(h, True).text or ""}
