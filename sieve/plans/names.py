"""Names for helper columns."""

from __future__ import annotations


def fresh(names: list[str], *wanted: str) -> list[str]:
    """Names that none of ``names`` has, in any case of letters."""
    out, taken = [], {n.lower() for n in names}
    for w in wanted:
        while w.lower() in taken:
            w = f"_{w}"
        taken.add(w.lower())
        out.append(w)
    return out
