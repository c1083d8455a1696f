"""Profiles as stacked bars in plain SVG."""

from __future__ import annotations

from html import escape

#: Colours of distinct, null and repeated values, of the size line and the natural key line.
BLUE, GREEN, ORANGE, SIZE_LINE, NK_LINE = "#3b6fb6", "#4c9f70", "#e08a3c", "#1f4e9c", "#c0392b"


def rrp_svg(rows: list[dict], nk_line: int | None = None, bar: int = 46, height: int = 220) -> str:
    """rows: attribute, category, n, dv, nv, ov in display order."""
    n = max([r["n"] for r in rows], default=0)
    scale = (height - 20) / n if n else 0
    out = [f'<svg xmlns="http://www.w3.org/2000/svg" width="{bar * len(rows) + 20}" height="{height + 70}" font-size="9" font-family="sans-serif">']
    for i, r in enumerate(rows):
        x, y = 10 + i * bar, float(height)
        for value, colour in ((r["dv"], BLUE), (r["nv"], GREEN), (r["ov"], ORANGE)):
            h = value * scale
            y -= h
            out.append(f'<rect x="{x}" y="{y:.1f}" width="{bar - 10}" height="{h:.1f}" fill="{colour}"><title>{escape(r["attribute"])}: {value}</title></rect>')
        out.append(f'<text x="{x}" y="{height - n * scale - 4:.1f}">{escape(r.get("category", ""))}</text>')
        out.append(f'<text x="{x}" y="{height + 12}" transform="rotate(40 {x} {height + 12})">{escape(r["attribute"])}</text>')
    for value, colour in ((n, SIZE_LINE), (nk_line, NK_LINE)):
        if value is not None:
            y = height - value * scale
            out.append(f'<line x1="0" x2="{bar * len(rows) + 20}" y1="{y:.1f}" y2="{y:.1f}" stroke="{colour}" stroke-width="2"/>')
    return "\n".join([*out, "</svg>"])
