"""A small, forgiving HTML parser that keeps what main-text extraction needs.

Block elements become nodes; inline elements only mark the text of the block they stand in.
"""

from __future__ import annotations

import html
import re
from collections import Counter

#: Elements whose content is no markup, those without an end tag, and those whose content is not shown once they are closed.
RAW = {"script", "style", "textarea", "title", "iframe", "noembed", "noframes", "xmp"}
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
UNSEEN = {"svg", "math", "template", "noscript", "object", "canvas", "select"}
INLINE = {
    "a", "abbr", "acronym", "b", "bdi", "bdo", "big", "cite", "code", "data", "del", "dfn", "em", "font", "i", "ins", "kbd", "label", "mark", "q", "rp", "rt",
    "ruby", "s", "samp", "small", "span", "strike", "strong", "sub", "sup", "time", "tt", "u", "var", "nobr", "picture", "audio", "video",
}
#: A start tag of the key closes an open element of these, up to the listed boundary elements.
CLOSES = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"})}
#: Start tags that can't stand in a drawing, formula or list of options, and so end one that was left open.
ENDS_UNSEEN = {
    "p", "div", "h1", "h2", "h3", "h4", "h5", "h6", "ul", "ol", "dl", "li", "table", "pre", "blockquote", "article", "section", "main", "aside", "nav", "header", "footer", "form",
    "figure", "body", "center", "hr", "br", "img",
}
#: Open elements at once, as in browsers; a deeper one takes the place of the innermost.
DEEPEST = 200
#: Tags of a page whose quotes may stay open; after so many, quotes no longer hide the end of a tag.
BROKEN_QUOTES = 16
_NAME = re.compile(r"/?([a-zA-Z][^\s/>]*)")
_PLAIN = re.compile(r"""[^"'>]*""")
_NAMES = re.compile(r"""\b(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+))""", re.I)
_WORD = re.compile(r"[a-z]+|[A-Z][a-z]*")
_LONG_NUMBER = re.compile(r"&#(?:0*[1-9][0-9]{7,}|[xX]0*[1-9a-fA-F][0-9a-fA-F]{6,});?")
_ZEROS = re.compile(r"&#([xX]?)0+(?=[0-9a-fA-F])")


def unescape(text: str) -> str:
    """Character references decoded; the frequent &amp; is taken apart first, which is the same."""
    if "&" not in text:
        return text
    if "&#" in text:  # numbers beyond all code points, and of any number of digits
        text = _ZEROS.sub(r"&#\1", _LONG_NUMBER.sub("\ufffd", text))
    return "&".join([html.unescape(p) if "&" in p else p for p in text.split("&amp;")])


def tokens(source: str):
    """(text, "", "") and ("", name, attributes) of the page in order; an end tag's name begins with a slash.

    Every character is looked at a bounded number of times: what is searched for and not found
    is not searched for again.
    """
    at, n, quotes = 0, len(source), BROKEN_QUOTES
    last = {c: source.rfind(c) for c in "\"'>"}
    find = source.find
    while at < n:
        begin = find("<", at)
        if begin < 0:
            yield source[at:], "", ""
            return
        if begin > at:
            yield source[at:begin], "", ""
        mark = source[begin + 1 : begin + 2]
        if mark in ("!", "?"):
            end = find("-->", begin + 4) + 2 if source.startswith("<!--", begin) else find("]]>", begin + 9) + 2 if source.startswith("<![CDATA[", begin) else find(">", begin)
            if source.startswith(("<!-->", "<!--->"), begin):
                end = find(">", begin)
            if end < begin:
                return
            at = end + 1
            continue
        name = _NAME.match(source, begin + 1)
        if name is None:
            yield "<", "", ""
            at = begin + 1
            continue
        at = rest = name.end()
        while True:
            at = _PLAIN.match(source, at).end()
            c = source[at : at + 1]
            if c == ">" or not c:
                break
            if not quotes or last[c] <= at:
                at = n
                break
            at = find(c, at + 1) + 1
        if at >= n:  # quotes that stay open, or no end at all
            quotes = max(0, quotes - 1)
            if last[">"] < rest:
                return
            at = find(">", rest)
        yield "", ("/" if source[begin + 1] == "/" else "") + name.group(1).lower(), source[rest:at]
        at += 1
        if name.group(1).lower() in RAW and source[begin + 1] != "/" and source[at - 2] != "/":
            end = _ENDS[name.group(1).lower()].search(source, at)
            if end is None:
                return
            at = end.end()


class Page:
    """Nodes in document order: tag, parent, attribute words, whether they show, and pieces of text.

    `pieces` has (node, text, linked) in page order; None as text marks a block boundary.
    """

    __slots__ = ("tag", "parent", "words", "unseen", "pieces")

    def __init__(self, source: str):
        self.tag, self.parent, self.words, self.unseen = ["#root"], [-1], [()], set()
        self.pieces: list[tuple[int, str | None, bool]] = []
        self._parse(source)

    def _parse(self, source: str) -> None:
        tags, parents, words, pieces = self.tag, self.parent, self.words, self.pieces
        stack, opened, links = [0], Counter(), 0

        def close(k: int) -> None:
            """End the k-th open element and all inside it."""
            for node in stack[k:]:
                opened[tags[node]] -= 1
            if tags[stack[k]] in UNSEEN:
                self.unseen.add(stack[k])
            del stack[k:]

        def close_last(names, stop=()) -> bool:
            if not any(opened[x] for x in names):
                return False
            for k in range(len(stack) - 1, 0, -1):
                if tags[stack[k]] in names:
                    close(k)
                    return True
                if tags[stack[k]] in stop:
                    return False
            return False

        for text, name, rest in tokens(source):
            if text:
                pieces.append((stack[-1], text, links > 0))
                continue
            if name[0] == "/":
                name = name[1:]
                if name == "a":
                    links = max(0, links - 1)
                elif name not in INLINE:
                    if close_last((name,)):
                        links = 0
                    pieces.append((stack[-1], None, False))
                continue
            if name in ENDS_UNSEEN and (opened["svg"] or opened["math"] or opened["select"]):
                close_last(("svg", "math", "select"), ("template", "foreignobject"))
            if name in INLINE:
                links += name == "a"
                continue
            if name == "br":
                pieces.append((stack[-1], " ", False))
                continue
            if name in RAW or name in VOID:
                continue
            if opened["p"] and any(tags[s] == "p" for s in stack[-3:]):  # block content ends a paragraph
                close_last(("p",))
            if name in CLOSES:
                close_last(*CLOSES[name])
            if name in ("html", "body", "head") and opened[name]:
                continue
            if len(stack) > DEEPEST:
                close(len(stack) - 1)
            links = 0
            tags.append(name)
            parents.append(stack[-1])
            words.append(tuple(w.lower() for v in _NAMES.findall(rest) for w in _WORD.findall(v[0] or v[1] or v[2])) if "=" in rest else ())
            pieces.append((len(tags) - 1, None, False))
            if rest.endswith("/") and (opened["svg"] or opened["math"]):
                continue
            opened[name] += 1
            stack.append(len(tags) - 1)

    def hidden(self) -> set[int]:
        """Nodes in an element that doesn't show its content."""
        out = set(self.unseen)
        if out:
            out.update(v for v in range(min(out), len(self.tag)) if v in out or self.parent[v] in out and not out.add(v))
        return out

    def blocks(self, kept) -> list[str]:
        """Texts of the blocks in page order, from pieces whose node is kept."""
        out, held, hidden = [], [], self.hidden()
        for node, text, _ in self.pieces:
            if text is None:
                if held:
                    joined = " ".join(unescape("".join(held)).split())
                    if joined:
                        out.append(joined)
                    held = []
            elif kept[node] and node not in hidden:
                held.append(text)
        joined = " ".join(unescape("".join(held)).split())
        return [*out, joined] if joined else out


_ENDS = {name: re.compile(f"</{name}\\b[^>]*>", re.I) for name in RAW}
