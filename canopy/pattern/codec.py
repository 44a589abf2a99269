"""Pattern text: ``A(B,C(D))``; in queries also ``A(B,C//D)`` and ``A(/B)``.

A label is any text without ``( ) , /``. Children follow in parentheses.
``//`` before a child or between two labels is a descendant edge, the default;
``/`` is a child edge.
"""

from __future__ import annotations

from canopy.pattern.model import Pattern

SPECIAL = set("(),/")


def parse_edges(text: str) -> tuple[Pattern, tuple[bool, ...]]:
    """The pattern, and for each node whether the edge above it is a child edge."""
    labels: list[str] = []
    parent: list[int] = []
    child: list[bool] = []
    at = 0

    def edge() -> bool:
        nonlocal at
        if text.startswith("//", at):
            at += 2
        elif text.startswith("/", at):
            at += 1
            return True
        return False

    def node(up: int, is_child: bool) -> None:
        nonlocal at
        start = at
        while at < len(text) and text[at] not in SPECIAL:
            at += 1
        label = text[start:at].strip()
        if not label:
            raise ValueError(f"a label is missing at {start} in {text!r}")
        labels.append(label)
        parent.append(up)
        child.append(is_child)
        own = len(labels) - 1
        if at < len(text) and text[at] == "(":
            at += 1
            while True:
                while at < len(text) and text[at] == " ":
                    at += 1
                node(own, edge())
                if at < len(text) and text[at] == ",":
                    at += 1
                    continue
                if at < len(text) and text[at] == ")":
                    at += 1
                    break
                raise ValueError(f"',' or ')' is missing at {at} in {text!r}")
        elif at < len(text) and text[at] == "/":
            node(own, edge())

    node(-1, False)
    if text[at:].strip():
        raise ValueError(f"something follows the pattern at {at} in {text!r}")
    return Pattern(tuple(labels), tuple(parent)), tuple(child)


def parse(text: str) -> Pattern:
    return parse_edges(text)[0]


def show(p: Pattern, node: int = 0) -> str:
    inner = ",".join(show(p, c) for c in p.children[node])
    return f"{p.labels[node]}({inner})" if inner else p.labels[node]


def forest(text: str) -> list[Pattern]:
    """Trees in pattern text, parted by ``;``."""
    return [parse(t.strip()) for t in text.split(";") if t.strip()]


def dot(p: Pattern, name: str = "pattern") -> str:
    """Graphviz text of a pattern."""
    quote = lambda s: s.replace("\\", "\\\\").replace('"', '\\"')
    nodes = [f'  n{n} [label="{quote(x)}"];' for n, x in enumerate(p.labels)]
    edges = [f"  n{u} -> n{n};" for n, u in enumerate(p.parent) if u >= 0]
    return "\n".join([f"digraph {name} {{", *nodes, *edges, "}"])
