"""Table functions. Workers import this module, so nothing in it needs a session."""

from __future__ import annotations

import re

from . import codec


class TileCells:
    """Cells of one tile as rows."""

    def eval(self, tr: int, tc: int, singles: int, code: bytes, vals: bytes, edge: int):
        for r, c, w in zip(*(x.tolist() for x in codec.decode(bytes(code), None if vals is None else bytes(vals), singles))):
            yield tr * edge + r, tc * edge + c, w


class HtmlLinks:
    """Targets of the anchors of a page, in order."""

    def eval(self, html: str):
        for place, found in enumerate(re.finditer(r'<a\s[^>]*href="([^"]*)"', html or "")):
            yield place, found.group(1)
