"""Main text of web pages by wrappers: union-free regular expressions inferred from pages of the same host.

A page is a stream of tags and texts. Runs of equal groups of tokens are folded to repeated groups; then the streams
of several pages of a host are aligned one after another. Texts that differ become slots, tokens that only some pages
have become optional groups, and what is left is a wrapper. All pages of a host take part: pages of one folded
structure are merged where they are read, pages whose outer containers agree are a template, and each template of a
host has a wrapper of its own, aligned from all its structures. The container of the article is read off the wrapper:
among the elements that stand once in every page, the innermost that holds most of the slots' text outside menus,
notices and the like. Every page is then cut by the container of its template. Where that has none, the page's own
container is used, or its body.

Cases: null or empty html gives the empty text; elements may be nested to any depth; a page without host belongs to a host of its own kind; unclosed and
stray tags are taken as browsers do, roughly; equal pages align without slots, and then all texts count; repeated
rows give repeated rows; an empty table gives an empty table. Only the named columns are read.
"""

from __future__ import annotations

import hashlib
import html as html_lib
import json
import re
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localcoef.llm.store import written

#: Levels of containers that pages of one template have in common.
TEMPLATE_DEPTH = 4
#: Parts in which the structures of a template are aligned before these are aligned with one another.
PARTS = 64
#: Elements nested deeper are no containers by themselves; their text is that of the element above.
LEVELS = 200
#: Characters of pages of new structures after which a task hands on what it has merged.
HELD_CHARS = 16_000_000
#: Bytes of containers that are broadcast; more are shuffled.
BROADCAST_BYTES = 32_000_000

#: Kinds of HTML elements.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template iframe textarea select object svg math canvas title".split())
FOREIGN = frozenset(("svg", "math"))
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
CONTAINERS = frozenset("html body main article section div td center".split())
ENDS_PARAGRAPH = frozenset("address article aside blockquote center details dialog dd div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr li main menu nav ol p pre section table ul".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
SKIPPED = frozenset("nav footer aside form button dialog menu head".split())
_SIDE_WORDS = "ad|ads|advert|adverts|advertisement|advertising|banner|breadcrumb|breadcrumbs|comment|comments|commentlist|consent|cookie|cookies|disqus|disclaimer|footer|masthead|menu|menubar|modal|nav|navbar|navigation|newsletter|notice|notices|pager|pagination|popup|promo|promoted|recommended|related|replies|responses|search|share|sharing|sidebar|social|sponsor|sponsored|subscribe|toolbar|widget"
_SIDE = re.compile(rf"(?:^|[\s#_-])(?:{_SIDE_WORDS})(?:$|[\s#_-])")
_SIDE_WHOLE = frozenset(_SIDE_WORDS.split("|"))
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<![^>]*>|<\?[^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|([^<]+|<)", re.S)
_ATTRIBUTE = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_BLANK = re.compile(r"\s+")
_DIGITS = re.compile(r"[0-9]+")


def tokens(page: str):
    """(kind, name, signature or text): 'o' for opening tags, 'c' for closing ones, 't' for texts."""
    at, size = 0, len(page)
    while at < size:
        m = _TOKEN.match(page, at)
        if m is None:
            at += 1
            continue
        at = m.end()
        slash, name, attributes, text = m.groups()
        if text is not None:
            yield "t", "", text
        elif name is not None:
            name = name.lower()
            if slash:
                yield "c", name, name
                continue
            found = [(kind.lower(), x.lower()) for kind, *v in _ATTRIBUTE.findall(attributes) for x in v if x] if attributes else []
            marks = " ".join(x for kind, x in found if kind != "id") + "".join(f" #{x}" for kind, x in found if kind == "id")
            marks = _DIGITS.sub("0", marks)  # numbers of posts and columns do not tell elements apart
            if name in RAW:
                if name in FOREIGN and attributes.endswith("/"):
                    continue
                end = re.compile(rf"</{re.escape(name)}\s*>", re.I).search(page, at)
                at = end.end() if end else size
                continue
            yield "o", name, f"{name}.{marks}" if marks else name
            if attributes.endswith("/") and name in VOID:
                continue


def aside(name: str, signature: str, depth_in_container: bool = False) -> bool:
    """Whether an element is a menu, notice, advert, form or the like; inside a container only whole classes and roles tell."""
    if name in SKIPPED or (name == "header" and not depth_in_container):
        return True
    if "." not in signature:
        return False
    marks = signature.partition(".")[2]
    if depth_in_container:
        return not _SIDE_WHOLE.isdisjoint(marks.partition("#")[0].split())
    return bool(_SIDE.search(marks))


def doubtful(name: str, signature: str) -> bool:
    """Whether a part of a class or role, but no whole one, is a word for menus and the like; headings are in no doubt."""
    return "." in signature and name not in HEADINGS and bool(_SIDE.search(signature.partition(".")[2].partition("#")[0]))


@dataclass
class Tree:
    """An element of a page: its signature and its children, which are texts or elements."""

    name: str
    signature: str
    children: list = field(default_factory=list)


def parse(page: str) -> Tree:
    root = Tree("", "")
    stack = [root]
    for kind, name, value in tokens(page):
        if kind == "t":
            stack[-1].children.append(value)
        elif kind == "o":
            if name in ENDS_PARAGRAPH:
                _close(stack, "p", ("div", "article", "section", "td", "body", "li", "blockquote"))
            if name in ("li", "dt", "dd", "tr", "td", "th", "option"):
                _close(stack, name, ("ul", "ol", "dl", "table"))
            node = Tree(name, value)
            stack[-1].children.append(node)
            if name not in VOID:
                stack.append(node)
        else:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].name == name:
                    del stack[i:]
                    break
    return root


def _close(stack: list[Tree], name: str, limits: tuple) -> None:
    for i in range(len(stack) - 1, 0, -1):
        if stack[i].name == name:
            del stack[i:]
            return
        if stack[i].name in limits:
            return


# A wrapper is a list of nodes: ("o", signature), ("c", signature), ("t", text or None, characters, pages),
# ("+", nodes) for a repeated group and ("?", nodes) for an optional one.


def stream(node: Tree) -> list:
    """A parsed page as wrapper nodes, with inline markup taken as part of the text and blank texts dropped."""
    out: list = []
    run: list[str] = []

    def flush():
        text = _BLANK.sub(" ", "".join(run)).strip()
        run.clear()
        if text:
            out.append(("t", _short(text), len(text), 1))

    open_elements = [(iter(node.children), None)]  # with the signature to close, or None for inline markup
    while open_elements:
        children, end = open_elements[-1]
        for child in children:
            if isinstance(child, str):
                run.append(child)
            elif child.name in INLINE:
                run.append(" " if child.name == "br" else "")
                open_elements.append((iter(child.children), None))
                break
            else:
                flush()
                out.append(("o", child.signature))
                open_elements.append((iter(child.children), child.signature))
                break
        else:
            open_elements.pop()
            if end is not None:
                flush()
                out.append(("c", end))
    flush()
    return out


def _short(text: str) -> str:
    """A long text as its begin and a hash, so that wrappers stay small."""
    return text if len(text) <= 72 else text[:40] + hashlib.blake2b(text.encode("utf-8", "replace"), digest_size=16).hexdigest()


def key(node) -> str:
    """What of a node must agree in an alignment: texts all agree, groups agree by their nodes."""
    if node[0] == "t":
        return "#"
    if node[0] in "+?":
        return node[0] + "(" + " ".join(map(key, node[1])) + ")"
    return node[0] + node[1]


def merge(a, b):
    """Two nodes that agree, as one: different texts become a slot."""
    if a[0] == "t":
        return ("t", a[1] if a[1] == b[1] else None, a[2] + b[2], a[3] + b[3])
    if a[0] in "+?":
        return (a[0], [merge(x, y) for x, y in zip(a[1], b[1], strict=True)])
    return a


class _Items:
    """Wrapper nodes as nested items of siblings, each a number that stands for its structure and its nodes or items."""

    def __init__(self):
        self.numbers: dict = {}

    def _number(self, structure) -> int:
        return self.numbers.setdefault(structure, len(self.numbers))

    def of(self, nodes: list, siblings=None) -> list:
        """The items of a run of nodes; ``siblings`` may shorten the items of each element, innermost first."""
        siblings = siblings or (lambda items: items)
        levels: list[tuple] = [(None, [])]
        for n in nodes:
            if n[0] == "o":
                levels.append((n, []))
            elif n[0] == "c" and levels[-1][0] is not None and levels[-1][0][1] == n[1]:
                start, items = levels.pop()
                items = siblings(items)
                levels[-1][1].append((self._number(("o", n[1], *(x[0] for x in items))), [start, *items, n]))
            else:
                levels[-1][1].append(self.leaf(n))
        while len(levels) > 1:  # alignments may leave elements open
            start, items = levels.pop()
            levels[-1][1].extend([self.leaf(start), *items])
        return siblings(levels[0][1])

    def leaf(self, node: tuple) -> tuple:
        return (self._number(key(node)), [node])

    def repeated(self, groups: list[list]) -> tuple:
        """The item of a repeated group, merged from groups of equal items."""
        flat = [_nodes(g) for g in groups]
        group = flat[0]
        for other in flat[1:]:
            group = [merge(x, y) for x, y in zip(group, other, strict=True)]
        return self.leaf(group[0] if len(group) == 1 and group[0][0] == "+" else ("+", group))

    def shorter(self, items: list) -> list:
        """Runs of equal groups of siblings become repeated groups; shorter groups first, until nothing changes."""
        changed = True
        while changed:
            changed, width = False, 0
            while 2 * (width + 1) <= len(items):
                width += 1
                times = _repeats(np.array([x[0] for x in items]), width)
                if times is None:
                    continue
                out, i = [], 0
                while i < len(items):
                    n = int(times[i]) + 1 if i < len(times) else 1
                    out.append(self.repeated([items[i + k * width : i + (k + 1) * width] for k in range(n)]) if n > 1 else items[i])
                    i += n * width if n > 1 else 1
                items, changed = self.absorbed(out), True
        return items

    def absorbed(self, items: list) -> list:
        """One more instance beside a repeated group joins it."""
        out: list = []
        i = 0
        while i < len(items):
            item = items[i]
            node = item[1][0]
            if not isinstance(node, list) and node[0] == "+":
                inner = [x[0] for x in self.of(node[1])]
                w = len(inner)
                groups = [[item]]
                while i + 1 < len(items) and items[i + 1][0] == item[0]:
                    groups.append([items[i + 1]])
                    i += 1
                item = self.repeated(groups) if len(groups) > 1 else item
                plain = [item[1][0][1]]
                while [x[0] for x in items[i + 1 : i + 1 + w]] == inner:
                    plain.append(_nodes(items[i + 1 : i + 1 + w]))
                    i += w
                while len(out) >= w and [x[0] for x in out[-w:]] == inner:
                    plain.insert(0, _nodes(out[-w:]))
                    del out[-w:]
                if len(plain) > 1:
                    group = plain[0]
                    for other in plain[1:]:
                        group = [merge(x, y) for x, y in zip(group, other, strict=True)]
                    item = self.leaf(("+", group))
            out.append(item)
            i += 1
        return out


def _nodes(items: list) -> list:
    """The nodes of items, in order."""
    out, left = [], list(reversed(items))
    while left:
        x = left.pop()
        if isinstance(x[0], str):
            out.append(x)
        else:
            left += reversed(x[1])
    return out


def fold(nodes: list) -> list:
    """Runs of equal groups of siblings become repeated groups, in the innermost elements first."""
    items = _Items()
    return _nodes(items.of(nodes, items.shorter))


def _repeats(numbers: np.ndarray, width: int) -> np.ndarray | None:
    """For each place how often the group of so many numbers that starts there follows on itself, or None for nowhere."""
    same = numbers[width:] == numbers[:-width]
    differ = np.concatenate([np.flatnonzero(~same), [len(same)]])
    ahead = differ[np.searchsorted(differ, np.arange(len(same)))] - np.arange(len(same))
    times = ahead // width
    return times if times.any() else None


def _balanced(nodes: list) -> bool:
    depth = 0
    for n in nodes:
        depth += (n[0] == "o") - (n[0] == "c")
        if depth < 0:
            return False
    return depth == 0


#: Bits of the rows that an alignment keeps at once; longer streams are halved first.
ALIGN_BITS = 1 << 28


def common(a: list, b: list) -> list[tuple[int, int]]:
    """Places of a longest common subsequence, by rows of bits; time grows with the product of the lengths over 64."""
    numbers: dict = {}
    return _common([numbers.setdefault(x, len(numbers)) for x in a], [numbers.setdefault(x, len(numbers)) for x in b])


def _common(a: list[int], b: list[int]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    parts = [(0, len(a), 0, len(b))]
    while parts:
        i, j, k, m = parts.pop()
        while i < j and k < m and a[i] == b[k]:
            out.append((i, k))
            i, k = i + 1, k + 1
        while i < j and k < m and a[j - 1] == b[m - 1]:
            j, m = j - 1, m - 1
            out.append((j, m))
        if i == j or k == m:
            continue
        if (j - i) * (m - k) <= ALIGN_BITS or j - i == 1:
            out += [(i + x, k + y) for x, y in _matched(a[i:j], b[k:m])]
            continue
        half = (i + j) // 2
        before = _scores(a[i:half], b[k:m])
        after = _scores(a[half:j][::-1], b[k:m][::-1])[::-1]
        cut = k + int(np.argmax(before + after))
        parts += [(i, half, k, cut), (half, j, cut, m)]
    return sorted(out)


def _bit_rows(a: list[int], b: list[int]):
    """Row by row of a, the bits of b where the longest common subsequence does not grow."""
    places: dict[int, int] = {}
    for y, value in enumerate(b):
        places[value] = places.get(value, 0) | 1 << y
    whole = (1 << len(b)) - 1
    row = whole
    for value in a:
        met = row & places.get(value, 0)
        row = ((row + met) | (row - met)) & whole
        yield row


def _scores(a: list[int], b: list[int]) -> np.ndarray:
    """Length of the longest common subsequence of a and each prefix of b."""
    row = (1 << len(b)) - 1
    for row in _bit_rows(a, b):  # noqa: B007
        pass
    bits = np.unpackbits(np.frombuffer(row.to_bytes(len(b) // 8 + 1, "little"), np.uint8), bitorder="little")[: len(b)]
    return np.concatenate([[0], np.cumsum(1 - bits.astype(np.int64))])


def _matched(a: list[int], b: list[int]) -> list[tuple[int, int]]:
    rows = list(_bit_rows(a, b))
    out, x, y = [], len(a), len(b)
    while x and y:
        if rows[x - 1] >> (y - 1) & 1:
            y -= 1
        else:
            x -= 1
            if not x or rows[x - 1] >> (y - 1) & 1:
                y -= 1
                out.append((x, y))
    return out


def align(wrapper: list, page: list) -> list:
    """The wrapper that also takes the page: equal nodes merge, others become optional."""
    out: list = []
    i = k = 0
    for x, y in [*common([key(n) for n in wrapper], [key(n) for n in page]), (len(wrapper), len(page))]:
        for part in (wrapper[i:x], page[k:y]):
            out += _optional(part)
        if x < len(wrapper) and y < len(page):
            out.append(merge(wrapper[x], page[y]))
        i, k = x + 1, y + 1
    return _unite(out)


def _optional(part: list) -> list:
    """Nodes that only some pages have; groups that do not close what they open cannot be optional as one, and what is
    optional stays as it is, so that groups do not nest with every page."""
    if not _balanced(part):
        return [n if n[0] in "oc?" else ("?", [n]) for n in part]
    out: list = []
    run: list = []
    depth = 0
    for n in part:
        if n[0] == "?" and not depth:
            out += [("?", run)] if run else []
            out.append(n)
            run = []
        else:
            depth += (n[0] == "o") - (n[0] == "c")
            run.append(n)
    return out + ([("?", run)] if run else [])


def _unite(nodes: list) -> list:
    """Optional groups that stand together and agree are one."""
    out: list = []
    for n in nodes:
        if n[0] == "?" and out and out[-1][0] == "?" and key(out[-1]) == key(n):
            out[-1] = merge(out[-1], n)
        else:
            out.append(n)
    return out


def infer(pages: list[str]) -> list:
    return _aligned([fold(stream(parse(page))) for page in pages])


def _aligned(streams: list[list]) -> list:
    wrapper: list = []
    for k, nodes in enumerate(streams):
        wrapper = nodes if k == 0 else fold(align(wrapper, nodes))
    return wrapper


def expression(nodes: list) -> str:
    """The wrapper as a readable regular expression over tags and slots."""
    parts = []
    for n in nodes:
        if n[0] == "t":
            parts.append("#slot" if n[1] is None else json.dumps(n[1][:40], ensure_ascii=False))
        elif n[0] == "o":
            parts.append(f"<{n[1]}>")
        elif n[0] == "c":
            parts.append(f"</{n[1].partition('.')[0]}>")
        else:
            parts.append(f"({expression(n[1])}){n[0]}")
    return " ".join(parts)


def once(nodes: list) -> set[tuple]:
    """Paths of signatures that stand exactly once in a folded page."""
    seen: dict[tuple, int] = {}

    def walk(nodes, path, times):
        deeper = 0
        for n in nodes:
            if n[0] == "o":
                if len(path) < LEVELS:
                    path = (*path, n[1])
                    seen[path] = seen.get(path, 0) + times
                else:
                    deeper += 1
            elif n[0] == "c":
                path, deeper = (path, deeper - 1) if deeper else (path[:-1], 0)
            elif n[0] != "t":
                walk(n[1], path, 2 if n[0] == "+" else times)

    walk(nodes, (), 1)
    return {p for p, n in seen.items() if n == 1}


def container(wrapper: list, single: set[tuple] | None = None) -> list[str] | None:
    """Path of signatures of the element that holds the article, or None.

    Only elements whose path stands once in every page are taken: ``single``, or what stands once in the wrapper.
    """
    single = once(wrapper) if single is None else single
    weight: dict[tuple, float] = {}
    titles: dict[tuple, float] = {}
    flat = {"any": 0.0, "title": 0.0}

    def walk(nodes, path, skipped):
        deeper = 0
        for n in nodes:
            if n[0] == "o":
                name = n[1].partition(".")[0]
                inside = any(p.partition(".")[0] in ("article", "main") for p in path)
                path, deeper = ((*path, n[1]), 0) if len(path) < LEVELS else (path, deeper + 1)
                if skipped or aside(name, n[1], inside):
                    skipped += 1
                elif not deeper and path in single and name in CONTAINERS:
                    weight.setdefault(path, 0.0)
            elif n[0] == "c":
                path, deeper = (path, deeper - 1) if deeper else (path[:-1], 0)
                skipped = max(0, skipped - 1)
            elif n[0] == "t":
                if not skipped:
                    size = float(n[2]) if n[1] is None or not slots else 0.0
                    title = size if path and path[-1].partition(".")[0] == "h1" else 0.0
                    flat["any"] += size
                    flat["title"] += title
                    for k in range(1, len(path) + 1):
                        if path[:k] in weight:
                            weight[path[:k]] += size
                            titles[path[:k]] = titles.get(path[:k], 0.0) + title
            else:
                walk(n[1], path, skipped)

    slots = _has_slot(wrapper)
    walk(wrapper, (), 0)
    if not flat["any"]:
        return None
    best = None
    for path, w in weight.items():
        named = path[-1].partition(".")[0] in ("article", "main")
        whole = titles.get(path, 0.0) >= flat["title"] - 1e-9  # a title beside the text belongs to it
        if whole and w >= (0.5 if named else 0.75) * flat["any"] and (best is None or len(path) > len(best)):
            best = path
    if best is None:
        return None
    # an article or main above a nested part of it is the whole, and so is a main that holds more than its article
    above = [best[:k] for k in range(1, len(best) + 1) if best[:k] in weight]
    for kind in ("article", "main"):
        found = next((p for p in above if p[-1].partition(".")[0] == kind), None)
        if found and (len(found) == len(best) or kind == "article" or weight[found] > weight[best] or best[-1].partition(".")[0] != "article"):
            best = found
    return list(best)


def constant_asides(wrapper: list) -> list[list[str]]:
    """Paths of the doubtful elements whose text is the same in all pages, where texts of the wrapper differ at all."""
    varies: dict[tuple, bool] = {}

    def walk(nodes, path):
        deeper = 0
        for n in nodes:
            if n[0] == "o":
                path, deeper = ((*path, n[1]), 0) if len(path) < LEVELS else (path, deeper + 1)
                if not deeper and doubtful(n[1].partition(".")[0], n[1]):
                    varies.setdefault(path, False)
            elif n[0] == "c":
                path, deeper = (path, deeper - 1) if deeper else (path[:-1], 0)
            elif n[0] == "t":
                for k in range(1, len(path) + 1):
                    if path[:k] in varies:
                        varies[path[:k]] |= n[1] is None
            else:
                walk(n[1], path)

    if not _has_slot(wrapper):
        return []
    walk(wrapper, ())
    return [list(p) for p, v in varies.items() if not v]


def _has_slot(nodes: list) -> bool:
    return any((n[0] == "t" and n[1] is None) or (n[0] in "+?" and _has_slot(n[1])) for n in nodes)


def find(root: Tree, path: list[str]) -> Tree | None:
    """The element at a path; where several stand there, the innermost single element above them all."""
    level, single = [root], root
    for signature in path:
        level = [c for node in level for c in node.children if isinstance(c, Tree) and c.signature == signature]
        if not level:
            return None
        if len(level) == 1:
            single = level[0]
    return single


def _own(root: Tree) -> Tree:
    """The container of a page by itself, or its body."""
    path = container(fold(stream(root)))
    node = find(root, path) if path else None
    return node or _body(root) or root


def _body(root: Tree) -> Tree | None:
    left = [root]
    while left:
        node = left.pop()
        if node.name == "body":
            return node
        left += [c for c in reversed(node.children) if isinstance(c, Tree)]
    return None


def text_of(node: Tree, path: tuple = (), constant: frozenset = frozenset(), inside: bool = True) -> str:
    """The blocks of an element, without menus and the like, one to a line.

    Below the element, which stands at ``path``, ``constant`` holds the paths of further elements to leave out. What is
    not ``inside`` a container is the whole page; there whole ids tell as well, but not those of sections and headings.
    """
    blocks: list[str] = []
    run: list[str] = []

    def flush():
        text = _BLANK.sub(" ", html_lib.unescape("".join(run))).strip()
        run.clear()
        if text:
            blocks.append(text)

    def left_out(child, at):
        if aside(child.name, child.signature, True) or at in constant:
            return True
        return not inside and child.name in ("div", "ul") and child.signature.partition("#")[2] in _SIDE_WHOLE

    open_elements = [(iter(node.children), path, False)]
    while open_elements:
        children, path, block = open_elements[-1]
        for child in children:
            if isinstance(child, str):
                run.append(child)
            elif child.name in INLINE:
                if child.name == "br":
                    run.append(" ")
                elif not aside(child.name, child.signature, True):
                    open_elements.append((iter(child.children), path, False))
                    break
            else:
                flush()
                at = (*path, child.signature) if constant else ()
                if not left_out(child, at):
                    open_elements.append((iter(child.children), at, True))
                    break
        else:
            open_elements.pop()
            if block:
                flush()
    flush()
    return "\n".join(blocks)


def extract(page: str | None, paths: list[list[str] | None]) -> str:
    return _cut(parse(page), paths) if page else ""


def _cut(root: Tree, paths: list[list[str] | None], constant: frozenset = frozenset()) -> str:
    for path in paths:
        if path and (node := find(root, path)) is not None:
            return _text(root, node, constant)
    return _text(root, _own(root), constant)


def _text(root: Tree, node: Tree, constant: frozenset) -> str:
    return text_of(node, _place(root, node) if constant else (), constant, node.name not in ("", "html", "body"))


def _place(root: Tree, node: Tree) -> tuple | None:
    """The path of an element."""
    left = [(root, ())]
    while left:
        at, path = left.pop()
        if at is node:
            return path
        left += [(c, path if c.name in INLINE else (*path, c.signature)) for c in reversed(at.children) if isinstance(c, Tree)]
    return None


def _number(text: str) -> int:
    return int.from_bytes(hashlib.blake2b(text.encode("utf-8", "replace"), digest_size=8).digest(), "big", signed=True)


def template(root: Tree) -> int:
    """A number of the outer containers of a page, down to an article or main."""
    paths: set[str] = set()

    def walk(node, path, depth):
        for child in node.children:
            if isinstance(child, Tree) and child.name in CONTAINERS | {"main"} and not aside(child.name, child.signature):
                at = f"{path}/{child.signature}"
                paths.add(at)
                if depth < TEMPLATE_DEPTH and child.name not in ("article", "main"):
                    walk(child, at, depth + 1)

    walk(root, "", 1)
    return _number("\n".join(sorted(paths)))


def _structures(batches):
    """(host, template, structure, pages, nodes): pages of equal structure merged as they are read."""
    held: dict[tuple, tuple] = {}
    size = 0

    def handed():
        rows = [(*k, n, json.dumps(nodes, ensure_ascii=False)) for k, (n, nodes) in held.items()]
        held.clear()
        columns = zip(*rows, strict=True) if rows else ((),) * 5
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.string()), strict=True)], ["host", "template", "structure", "pages", "nodes"])

    for batch in batches:
        for host, page in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            page = page.as_py()
            root = parse(page)
            nodes = fold(stream(root))
            at = (host, template(root), _number(" ".join(map(key, nodes))))
            if at in held:
                n, old = held[at]
                held[at] = (n + 1, [merge(x, y) for x, y in zip(old, nodes, strict=True)])
            else:
                held[at] = (1, nodes)
                size += len(page)
            if size > HELD_CHARS:
                yield handed()
                size = 0
    yield handed()


def _part(frame):
    """One part of a template's structures as one wrapper, and the paths that stand once in all of them."""
    import pandas as pd

    by: dict[int, list] = {}
    for at, text in zip(frame["structure"], frame["nodes"], strict=True):
        nodes = json.loads(text)
        by[at] = [merge(x, y) for x, y in zip(by[at], nodes, strict=True)] if at in by else nodes
    wrapper, single = _aligned([by[k] for k in sorted(by)]), set.intersection(*map(once, by.values()))
    return pd.DataFrame({"host": [frame["host"].iloc[0]], "template": [frame["template"].iloc[0]], "part": [frame["part"].iloc[0]], "pages": [frame["pages"].sum()], "nodes": [json.dumps(wrapper, ensure_ascii=False)], "single": [json.dumps(sorted(single), ensure_ascii=False)]})


def _whole(frame):
    """The wrapper of a template from those of its parts."""
    import pandas as pd

    frame = frame.sort_values("part")
    wrapper = _aligned([json.loads(x) for x in frame["nodes"]])
    single = set.intersection(*[set(map(tuple, json.loads(x))) for x in frame["single"]])
    return pd.DataFrame({"host": [frame["host"].iloc[0]], "template": [frame["template"].iloc[0]], "n_pages": [frame["pages"].sum()], "wrapper": [expression(wrapper)], "container": [json.dumps(container(wrapper, single), ensure_ascii=False)], "constant": [json.dumps(constant_asides(wrapper), ensure_ascii=False)]})


def wrappers(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """Per host and template: the number of its pages, its wrapper as an expression, and as JSON the article's container and
    the paths of elements that look like menus and never change.

    Every page takes part. A template's structures are aligned in parts by a hash, so a host with very many pages is no
    burden for one task.
    """
    given = pages.where(F.col(html_col).isNotNull()).select(_host(F.col(url_col)).alias("host"), F.col(html_col).cast("string").alias("html"))
    merged = given.mapInArrow(_structures, "host string, template long, structure long, pages long, nodes string")
    parts = merged.withColumn("part", F.pmod("structure", F.lit(PARTS))).groupBy("host", "template", "part").applyInPandas(_part, "host string, template long, part long, pages long, nodes string, single string")
    return parts.groupBy("host", "template").applyInPandas(_whole, "host string, template long, n_pages long, wrapper string, container string, constant string")


def _host(url):
    return F.lower(F.regexp_extract(F.coalesce(url, F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1))


def extract_pages(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """Per row: the id, the url, the main text and its code points."""
    spark = pages.sparkSession
    known = written(wrappers(pages, url_col, html_col).where("container <> 'null' or constant <> '[]'").select("host", "template", F.concat(F.lit("["), "container", F.lit(","), "constant", F.lit("]")).alias("container")), "wrappers")
    size = known.agg(F.sum(F.length("host") + F.length("container") + 64).alias("n")).first()["n"] or 0
    rows = pages.select(F.col(id_col).alias("id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"), _host(F.col(url_col)).alias("host"))
    kind = pages.select(id_col).schema[0].dataType.simpleString()
    small = size <= broadcast_bytes
    if small:
        shared = spark.sparkContext.broadcast({(r["host"], r["template"]): r["container"] for r in known.collect()})
    else:
        rows = rows.mapInArrow(_with_template, f"id {kind}, url string, html string, host string, template long").join(known, ["host", "template"], "left").select("id", "url", "html", "container")

    def run(batches):
        @lru_cache(4096)
        def cuts(text):
            path, constant = json.loads(text)
            return path, frozenset(map(tuple, constant))

        for batch in batches:
            texts = []
            for page, given in zip(batch.column(2), batch.column(3).to_pylist(), strict=True):
                page = page.as_py()
                if not page:
                    texts.append("")
                    continue
                root = parse(page)
                own = shared.value.get((given, template(root))) if small else given
                path, constant = cuts(own) if own else (None, frozenset())
                texts.append(_cut(root, [path], constant))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], [id_col, url_col, "text", "n_chars"])

    return rows.mapInArrow(run, f"`{id_col}` {kind}, `{url_col}` string, text string, n_chars long")


def _with_template(batches):
    for batch in batches:
        found = pa.array([template(parse(page.as_py() or "")) for page in batch.column(2)], pa.int64())
        yield pa.RecordBatch.from_arrays([*batch.columns, found], ["id", "url", "html", "host", "template"])
