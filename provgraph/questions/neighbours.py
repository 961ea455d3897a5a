"""Joins of a question on nearness or on touching tiles, read as joins on grid cells: the same rows, without trying all pairs."""
from __future__ import annotations

import math
import re

from provgraph.operators.spatial import CELL
from provgraph.questions.templates import GAP, POINTS

#: Whole layers with boxes, and parts of one; of other sources nothing is known.
_BOXES = r"(?:entity|crowd|\(select \* from (?:entity|crowd)(?: where [^()]*)?\)|" + re.escape(POINTS) + ")"
_TILES = r"\(select tx, ty from entity\b(?:[^()]|\([^()]*\))*\)"
#: A condition may end or go on with more of them.
_END = r"(?=\s*(?:$|\)|(?:and|where|group|order|limit)\b))"
_NEAR = re.compile(rf"\bfrom\s+(?P<a>{_BOXES})\s+a\s+join\s+(?P<b>{_BOXES})\s+b\s+on\s+(?P<on>a\.city\s*=\s*b\.city\s+and\s+(?:a\.city\s*=\s*\d+\s+and\s+)?{re.escape(GAP)}\s*<=\s*(?P<d2>\d+)){_END}")
_TOUCH = re.compile(rf"\bfrom entity (?P<e>\w+) join (?P<b>{_TILES}) (?P<d>\w+) on (?P<on>abs\((?P=e)\.tx - (?P=d)\.tx\) \+ abs\((?P=e)\.ty - (?P=d)\.ty\) = 1){_END}")


def _cells(source: str, reach: int, cell: int) -> str:
    """``source`` with a row for each grid cell that a box touches within ``reach``."""
    rows = source[1:-1] if source.startswith("(") else f"select * from {source}"
    span = lambda v: f"sequence(floor(({v}0 - {reach}) / {cell}), floor(({v}1 + {reach}) / {cell}))"
    return f"(select * from ({rows}) _s lateral view explode({span('x')}) _u as _cx lateral view explode({span('y')}) _v as _cy)"


def _near(m: re.Match) -> str:
    """A pair within reach counts in the one cell of the lower corner of what box b and the widened box a share."""
    reach = math.isqrt(int(m["d2"])) + 1
    cell = max(CELL, reach)
    corner = lambda v: f"a._c{v} = floor(greatest(a.{v}0 - {reach}, b.{v}0) / {cell})"
    return f"from {_cells(m['a'], reach, cell)} a join {_cells(m['b'], 0, cell)} b on a._cx = b._cx and a._cy = b._cy and {corner('x')} and {corner('y')} and {m['on']}"


def _touching(m: re.Match) -> str:
    """A tile is dealt to the four that touch it."""
    around = "array(" + ", ".join(f"named_struct('x', tx + {i}, 'y', ty + {j})" for i, j in ((1, 0), (-1, 0), (0, 1), (0, -1))) + ")"
    return f"from entity {m['e']} join (select * from {m['b']} _s lateral view inline({around}) _n as _nx, _ny) {m['d']} on {m['e']}.tx = {m['d']}._nx and {m['e']}.ty = {m['d']}._ny and {m['on']}"


def indexed(text: str, boxes: bool = True) -> str:
    """``text`` with such joins keyed by cell.

    Whatever is not written just so stays as it is: other sources, conditions with ``or``, and queries whose columns
    aren't named, for the keys would show.  Without ``boxes`` joins on nearness stay too: the measure takes a box
    without coordinates to be near to all others.
    """
    for pattern, keyed in ((_NEAR, _near), (_TOUCH, _touching))[0 if boxes else 1 :]:

        def put(m: re.Match, text=text, keyed=keyed) -> str:
            head = text[: m.start()]
            listed = head[head.lower().rfind("select") :]
            if re.search(r"(select|distinct|,|\.)\s*\*", listed, re.I) or re.search(r"\bor\b", text[m.end() :], re.I):
                return m[0]
            return keyed(m)

        text = pattern.sub(put, text)
    return text
