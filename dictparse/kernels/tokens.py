"""From factors back to text, and factors written out."""

from __future__ import annotations

from dictparse.kernels.parse import Factor


def decode(phrases: list[Factor], entries: list[Factor] | None = None, scheme: str = "pair_cut") -> str:
    """The text of a parse. References are to the entries where they are separate, else to the phrases; begin and length tell their texts."""
    table = phrases if entries is None else entries
    reach = 1 if scheme == "seeded" else 0
    whole, size = "", 0  # the text so far: a plain local, which Python extends in place
    for _, length, kind, ref1, sym1, ref2, sym2, _ in phrases:
        if sym1 is not None:
            piece = sym1
        elif ref1:
            begin, n, *_ = table[ref1 - 1]
            piece = whole[begin : begin + n + reach]
            while len(piece) < n + reach:  # a seeded entry may end with the symbol now being written: the first of its own copy
                piece += piece[len(piece) - (size - begin)]
        else:
            piece = ""
        if kind == "repeat":
            piece *= -(-length // len(piece))
        elif kind in ("combine", "extend"):
            if sym2 is not None:
                piece += sym2
            elif ref2:
                begin, n, *_ = table[ref2 - 1]
                piece += whole[begin : begin + n]
        piece = piece[:length]
        whole += piece
        size += len(piece)
    return whole


def written(token: Factor) -> str:
    """A token in one line: parts joined by +, a power as ^k, a cut as |length."""
    _, length, kind, ref1, sym1, ref2, sym2, power = token
    part = lambda ref, sym: repr(sym) if sym is not None else f"#{ref}" if ref else "0"
    if kind == "repeat":
        return f"{part(ref1, sym1)}^{power}|{length}"
    if kind in ("combine", "extend"):
        return f"{part(ref1, sym1)}+{part(ref2, sym2)}|{length}"
    return f"{part(ref1, sym1)}|{length}"
