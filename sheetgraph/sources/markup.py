"""Tagged text as the runs of a workbook's string item."""

from __future__ import annotations

import re
from xml.sax.saxutils import escape, unescape

PIECES = re.compile(r'<(/?)(b|i|u|strike|font)(?: color="#([0-9a-fA-F]{6})")?>|([^<]+|<)')


def runs_xml(text: str) -> str:
    """One plain item, or a run for each piece between tags."""
    if not re.search(r"<(b|i|u|strike|font)[ >]", text):
        return f'<t xml:space="preserve">{escape(text)}</t>'
    open_: list[tuple[str, str | None]] = []
    out = []
    for closing, tag, color, piece in PIECES.findall(text):
        if closing:
            for k in range(len(open_) - 1, -1, -1):
                if open_[k][0] == tag:
                    del open_[k]
                    break
        elif tag:
            open_.append((tag, color))
        else:
            style = "".join(f'<color rgb="FF{c.upper()}"/>' if t == "font" else f"<{t}/>" for t, c in open_ if t != "font" or c)
            out.append(f'<r>{f"<rPr>{style}</rPr>" if style else ""}<t xml:space="preserve">{escape(unescape(piece))}</t></r>')
    return "".join(out)
