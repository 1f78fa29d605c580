"""A forgiving HTML reader: block elements and runs of inline text, with the counts that features are made of."""

from __future__ import annotations

import html
import re

#: Elements that start and end a block (fixed values).
BLOCKS = frozenset(
    "html head body address article aside blockquote center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 header hgroup hr li main menu nav ol p pre section search summary table caption tbody td tfoot th thead tr ul legend xmp".split()
)
#: Scripts, styles, controls of forms and what only old or scriptless readers show: their text is never taken. Then
#: those whose content is no markup. Formulas, drawings and media are read as inline text.
UNSEEN = frozenset("script style noscript template iframe select datalist textarea button option head title noframes noembed".split())
RAW = frozenset("script style textarea title iframe noframes noembed noscript".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: What an element's start tag ends, if it is open in the nearest of the scopes.
CLOSES = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "tbody": ("tr", "td", "th", "thead", "tbody"), "tfoot": ("tr", "td", "th", "tbody"), "option": ("option",)}
SCOPES = {"li": ("ul", "ol", "menu", "dir"), "dt": ("dl",), "dd": ("dl",), "tr": ("table",), "td": ("table", "tr"), "th": ("table", "tr"), "tbody": ("table",), "tfoot": ("table",), "option": ("select", "datalist")}

_TAG = re.compile(r"""<(?:!--(?P<comment>)|(?P<close>/?)(?P<name>[a-zA-Z][^\s/>]*+)(?P<attrs>(?:[^>"']++|"[^"]*+"|'[^']*+')*+)>|(?P<broken>/?[a-zA-Z][^>]*+)>|[!?/][^>]*+>)""")
_OPEN = re.compile(r"<[a-zA-Z/!?]")
_ATTR = re.compile(r"""([^\s=/"'>]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")
#: Deeper elements become children of the last one that may have any.
DEEPEST = 512
_HIDDEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)


class Node:
    """A block element, or a run of inline text (tag `#run`) in one. unseen: its text is never taken; hidden: its
    markup hides it, which is a feature and not a verdict."""

    __slots__ = ("tag", "parent", "children", "tokens", "depth", "unseen", "hidden", "text", "linked", "marks", "controls", "y")

    def __init__(self, tag: str, parent: Node | None, tokens: str = "", unseen: bool = False, hidden: bool = False):
        self.tag, self.parent, self.children, self.tokens = tag, parent, [], tokens
        self.depth = parent.depth + 1 if parent else 0
        self.unseen = unseen or bool(parent and parent.unseen)
        self.hidden = hidden or bool(parent and parent.hidden)
        self.text, self.linked, self.marks, self.controls, self.y = "", 0, 0, 0, 0


def parse(source: str) -> tuple[Node, list[Node]]:
    """(root, nodes in page order). White space of a run is one blank, ends are trimmed, empty runs are left out."""
    root = Node("#root", None)
    nodes, at, top, buffer = [root], 0, root, []
    linked = marks = 0
    in_link = False
    size = len(source)
    tags_end = source.rfind(">") + 1  # no tag ends beyond, and none is looked for there

    def flush() -> None:
        nonlocal linked, marks
        if buffer:
            text = "".join(buffer)
            buffer.clear()
            if not top.unseen:
                text = " ".join((html.unescape(text) if "&" in text else text).split())
                if text:
                    run = Node("#run", top)
                    run.text, run.linked, run.marks = text, min(linked, len(text)), marks
                    top.children.append(run)
                    nodes.append(run)
        linked = marks = 0

    while at < size:
        m = _TAG.search(source, at, tags_end)
        cut = None if m else _OPEN.search(source, max(at, tags_end))  # an unfinished tag or comment ends the page
        stop = m.start() if m else cut.start() if cut else size
        if stop > at:
            piece = source[at:stop]
            buffer.append(piece)
            if in_link:
                linked += len(piece)
        if not m:
            break
        at = m.end()
        if m["comment"] is not None:
            end = source.find("-->", at)
            at = end + 3 if end >= 0 else size
            continue
        name = m["name"]
        if name is None:
            if m["broken"] is None:
                continue
            name, attrs, closing = re.match(r"/?([a-zA-Z][^\s/>]*)", m["broken"])[1].lower(), "", m["broken"][0] == "/"
        else:
            name, attrs, closing = name.lower(), m["attrs"], bool(m["close"])
        if closing:
            if name == "a":
                in_link = False
            elif name in BLOCKS or name in UNSEEN:
                spot = top
                while spot is not root and spot.tag != name:
                    spot = spot.parent
                if spot is not root:
                    flush()
                    top, in_link = spot.parent, False
            else:
                marks += 1
            continue
        if name == "br":
            buffer.append(" ")
            continue
        if name == "a":
            in_link = True
            continue
        if name in BLOCKS or name in UNSEEN:
            if name in BLOCKS:
                flush()
                if top.tag == "head" or top.tag == "p" and name not in ("html", "head", "body"):
                    if name != "head":
                        top = top.parent
                        in_link = False
                ends = CLOSES.get(name)
                if ends:
                    spot, last, scopes = top, None, SCOPES[name]
                    while spot is not root and spot.tag not in scopes:
                        if spot.tag in ends:
                            last = spot
                        spot = spot.parent
                    if last:
                        top, in_link = last.parent, False
            if name in VOID:
                continue
            found = {k.lower(): (a or b or c) for k, a, b, c in _ATTR.findall(attrs)} if attrs.strip() else {}
            hidden = "hidden" in found or found.get("aria-hidden") == "true" or bool(_HIDDEN.search(found.get("style", "")))
            if name in RAW:
                end = re.compile(f"</{name}", re.I).search(source, at)
                at = end.start() if end else size
                if end:
                    close = source.find(">", at)
                    at = close + 1 if close >= 0 else size
                continue
            if name in UNSEEN and name not in BLOCKS:
                flush()
                if name in ("select", "button"):
                    top.controls += 1
            node = Node(name, top, " ".join(found.get(k, "") for k in ("class", "id", "role", "itemprop") if k in found), name in UNSEEN, hidden)
            top.children.append(node)
            nodes.append(node)
            if node.depth < DEEPEST and (name in BLOCKS or not attrs.rstrip().endswith("/")):
                top = node
        elif name in ("input", "label"):
            top.controls += 1
        else:
            marks += 1
    flush()
    return root, nodes
