"""What a parse is asked for, and the schemas of its results."""

from __future__ import annotations

from dataclasses import dataclass

from dictparse.kernels.lce import BACKENDS
from dictparse.kernels.parse import LOOKAHEADS, SCHEMES
from dictparse.kernels.trie import CHILDREN

#: Columns of a factor. begin and end are 1-based and inclusive; ref2 = 0 is the empty factor.
FACTOR = [
    ("x", "int"), ("beg", "long"), ("fin", "long"), ("len", "int"), ("kind", "string"), ("ref1", "int"), ("sym1", "string"),
    ("ref2", "int"), ("sym2", "string"), ("power", "int"),
]
#: Columns of a text's summary.
SUMMARY = [
    ("n", "long"), ("sigma", "int"), ("z", "long"), ("combine_n", "long"), ("cut_n", "long"), ("repeat_n", "long"), ("trie_nodes", "long"),
    ("split_nodes", "long"), ("child_steps", "long"), ("compare_steps", "long"), ("kernel_ms", "double"), ("peak_mb", "double"),
]


@dataclass(frozen=True)
class ParseSpec:
    """A validated parse: scheme, look-ahead, and how it is carried out.

    symbols: 'codepoint' or 'byte' (of UTF-8). stop_above: give up a text once it has more factors (its z is then null). counters: a
    summary says how many lookups and comparisons were made, else they are null where a count does without tokens.
    """

    scheme: str
    lookahead: str = "none"
    symbols: str = "codepoint"
    lce: str = "direct"
    children: str = "hash"
    fused: bool = True
    symbol_runs: bool = True
    stop_above: int | None = None
    counters: bool = False

    def __post_init__(self) -> None:
        for value, known in ((self.scheme, SCHEMES), (self.lookahead, LOOKAHEADS), (self.symbols, ("codepoint", "byte")), (self.lce, BACKENDS), (self.children, CHILDREN)):
            if value not in known:
                raise ValueError(f"{value!r} is none of {', '.join(known)}")
        if self.children == "ternary" and self.scheme not in ("step", "seeded"):
            raise ValueError("ternary children are for step and seeded")

    @property
    def name(self) -> str:
        return self.scheme if self.lookahead == "none" else f"{self.scheme}+{self.lookahead}"

    @property
    def options(self) -> dict:
        return {"lce_kind": self.lce, "children": self.children, "fused": self.fused, "symbol_runs": self.symbol_runs, "stop_above": self.stop_above}


def named(name: str, **options) -> ParseSpec:
    """'pair_run' or 'pair_run+flex_fixed'."""
    scheme, _, lookahead = name.partition("+")
    return ParseSpec(scheme, lookahead or "none", **options)


def columns(pairs: list[tuple[str, str]]) -> str:
    return ", ".join(f"{name} {kind}" for name, kind in pairs)


#: A text's factors as one array.
FACTOR_LIST = "array<struct<" + ",".join(f"{n}:{'bigint' if k == 'long' else k}" for n, k in FACTOR) + ",piece:string>>"
