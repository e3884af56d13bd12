"""Greedy and look-ahead parses of one text.

A factor is a tuple (begin, length, kind, ref1, sym1, ref2, sym2, power), begin 0-based; see `dictparse.plans.spec` for the columns.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from itertools import islice

from dictparse.kernels import lce as extensions
from dictparse.kernels import search
from dictparse.kernels.lce import Text
from dictparse.kernels.trie import NEVER, RadixDictionary

Factor = tuple[int, int, str, int | None, str | None, int | None, str | None, int | None]
PAIRS = ("pair", "pair_cut", "pair_run")
SCHEMES = (*PAIRS, "step", "seeded", "step_run")
LOOKAHEADS = ("none", "flex_fixed", "flex_own", "flex_longest")


def _symbol(text: Text, at: int) -> str:
    c = text[at]
    return c if isinstance(c, str) else chr(c)


@dataclass
class Rules:
    """What a scheme allows at a place of the text, given its dictionary."""

    text: Text
    scheme: str
    lce_kind: str = "direct"
    children: str = "hash"
    fused: bool = True
    symbol_runs: bool = True
    trie: RadixDictionary = field(init=False)

    def __post_init__(self) -> None:
        self.n = len(self.text)
        self.trie = RadixDictionary(self.text, self.children)
        self.lce = extensions.make(self.text, self.lce_kind) if self.scheme in ("pair_run", "step_run") else None
        # entries of seeded parses reach one symbol into what follows, which may be the current one
        self.slack = 1 if self.scheme == "seeded" else 0

    def add(self, begin: int, length: int, x: int) -> None:
        """The entry that a factor leaves in the dictionary."""
        if self.scheme == "seeded":
            length += 1
            if begin + length > self.n:
                return
        self.trie.insert(begin, length, x)

    def _first(self, at: int, gate: int, lce, extra: search.Extra):
        return (search.fused_first if self.fused else search.separate_first)(self.trie, at, gate, lce, extra)

    def best(self, at: int, gate: int = NEVER, extra: search.Extra = None) -> Factor:
        """The greedy factor at a place."""
        return getattr(self, "_pair" if self.scheme in PAIRS else "_" + self.scheme)(at, gate + self.slack, extra)

    def _pair(self, at: int, gate: int, extra: search.Extra) -> Factor:
        text, n, cuts = self.text, self.n, self.scheme != "pair"
        entry, size, cut, cut_size, base, power_size = self._first(at, gate, self.lce, extra)
        ref1, sym1 = (entry, None) if size > 1 else (None, _symbol(text, at))
        size = max(size, 1)
        if at + size == n:
            ref2, sym2, rest = 0, None, 0
        else:
            second, rest = search.fused_second(self.trie, at + size, gate, cuts, extra)
            ref2, sym2 = (second, None) if rest > 1 else (None, _symbol(text, at + size))
            rest = max(rest, 1)
        length = size + rest
        if cuts and cut_size > length:
            length, found = cut_size, (at, cut_size, "cut", cut, None, None, None, 1)
        else:
            found = (at, length, "combine", ref1, sym1, ref2, sym2, None)
        if self.lce:
            base, power_size = search.with_symbol(self.trie, at, self.lce, base, power_size)
            if power_size > length:
                found = self._power(at, power_size, base, extra)
        return found

    def _power(self, at: int, length: int, base: int, extra: search.Extra = None) -> Factor:
        size = 1 if not base else extra[1] if extra and base == extra[2] else self.lengths[base]
        return (at, length, "repeat", base or None, None if base else _symbol(self.text, at), None, None, -(-length // size))

    def _step(self, at: int, gate: int, extra: search.Extra) -> Factor:
        entry, size = search.fused_first(self.trie, at, gate, None, extra)[:2]
        if at + size == self.n:
            return (at, size, "entry", entry, None, None, None, None)
        return (at, size + 1, "extend", entry, None, None, _symbol(self.text, at + size), None)

    def _seeded(self, at: int, gate: int, extra: search.Extra) -> Factor:
        entry, size = search.fused_first(self.trie, at, gate, None, extra)[:2]
        return (at, size, "entry", entry, None, None, None, None) if size > 1 else (at, 1, "entry", None, _symbol(self.text, at), None, None, None)

    def _step_run(self, at: int, gate: int, extra: search.Extra) -> Factor:
        entry, size, cut, cut_size, base, power_size = self._first(at, gate, self.lce, extra)
        found = (at, size, "entry", entry, None, None, None, None) if at + size == self.n else (at, size + 1, "extend", entry, None, None, _symbol(self.text, at + size), None)
        if cut_size > found[1]:
            found = (at, cut_size, "cut", cut, None, None, None, 1)
        if self.symbol_runs:
            base, power_size = search.with_symbol(self.trie, at, self.lce, base, power_size)
        if power_size > found[1]:
            found = self._power(at, power_size, base, extra)
        return found

    #: length of every factor so far, by index
    lengths: list[int] = field(default_factory=lambda: [0], init=False)


def clip(token: Factor, length: int, base_length: int) -> Factor:
    """A greedy factor cut to fewer symbols; a power within its base is a cut of it."""
    if length == token[1]:
        return token
    at, _, kind, ref1, sym1, ref2, sym2, power = token
    if kind == "repeat":
        power = -(-length // base_length)
        if power == 1 and sym1 is None:
            kind = "cut"
    return (at, length, kind, ref1, sym1, ref2, sym2, power)


def greedy(rules: Rules) -> Iterator[Factor]:
    at, x = 0, 0
    while at < rules.n:
        found = rules.best(at)
        yield found
        x += 1
        rules.lengths.append(found[1])
        rules.add(at, found[1], x)
        at += found[1]


def greedy_reach(rules: Rules) -> Callable[[int], int]:
    """The function that gives the length of the greedy factor at a place, with the dictionary as it was when the parse stood there."""
    text, trie, get = rules.text, rules.trie, rules.trie.get
    label, size, own, own_end, first_end = trie.label, trie.size, trie.entry, trie.entry_end, trie.first_end
    n, slack, starts, powers, extension = len(text), rules.slack, text.startswith, rules.scheme == "pair_run", rules.lce

    def measure(p: int) -> int:
        gate = p + slack
        node = done = whole = reach = 0
        here, first = p, text[p]
        while here < n:
            child = get(node, text[here])
            if child is None or first_end[child] > gate:
                break
            s = size[child]
            if s > 1:
                place = label[child]
                if not starts(text[place : place + s], here):
                    done += 1 + extensions.first_difference(text, place + 1, here + 1, min(s, n - here) - 1)
                    break
            done += s
            here += s
            node = child
            if own[node] and own_end[node] <= gate:
                whole = done
                if powers and here < n and text[here] == first:
                    reach = max(reach, done + extension(p, here))
        length = whole or 1
        if slack:
            return length
        node, rest, here = 0, 0, p + length
        if here < n:
            while here < n:
                child = get(node, text[here])
                if child is None or first_end[child] > gate:
                    break
                s = size[child]
                if s > 1:
                    place = label[child]
                    if not starts(text[place : place + s], here):
                        rest += 1 + extensions.first_difference(text, place + 1, here + 1, min(s, n - here) - 1)
                        break
                rest += s
                here += s
                node = child
            length += rest or 1
        if powers and p + 1 < n and text[p + 1] == first:
            reach = max(reach, 1 + extension(p, p + 1))
        return max(length, done, reach)

    return measure


class Parse:
    """A parse: its phrases, its entries where these aren't the phrases, and the rules with their dictionary and counters."""

    def __init__(self, text: Text, scheme: str, lookahead: str = "none", stop_above: int | None = None, **options):
        if scheme not in SCHEMES or lookahead not in LOOKAHEADS:
            raise ValueError(f"unknown parse {scheme}/{lookahead}")
        if lookahead != "none" and scheme == "pair":
            raise ValueError("look-ahead needs a scheme with a prefix-closed dictionary")
        if lookahead == "flex_own" and scheme == "seeded":
            raise ValueError("a seeded parse's entries aren't its phrases")
        self.rules = Rules(text, scheme, **options)
        self.entries: list[Factor] | None = None
        found = greedy(self.rules) if lookahead == "none" else getattr(self, "_" + lookahead)()
        self.phrases = [*(found if stop_above is None else islice(found, stop_above + 1))]
        # a parse that is given up has one phrase too many, and no count
        self.given_up = stop_above is not None and len(self.phrases) > stop_above

    def _clipped(self, token: Factor, length: int) -> Factor:
        return clip(token, length, self.rules.lengths[token[3]] if token[2] == "repeat" and token[3] else 1)

    def _flex_fixed(self) -> Iterator[Factor]:
        """All greedy factors are entries; a place's reach depends on the place only, so it is kept."""
        rules = self.rules
        self.entries = [*greedy(rules)]
        n, at = rules.n, 0
        reach: dict[int, int] = {n: 0}
        measure = greedy_reach(rules) if rules.scheme in ("pair_cut", "pair_run", "seeded") else lambda p: rules.best(p, p)[1]

        def reach_at(p: int) -> int:
            if p not in reach:
                reach[p] = measure(p)
            return reach[p]

        # places whose reach ends furthest, of those up to where the current factor could end; a chosen place's factor never ends
        # before the last one's, so the range only moves on
        best: deque[int] = deque()
        upto = 0
        while at < n:
            end = at + reach_at(at)
            for p in range(max(upto, at) + 1, end + 1):
                far = p + reach_at(p)
                while best and best[-1] + reach[best[-1]] <= far:  # of equal ones the longer factor
                    best.pop()
                best.append(p)
            upto = max(upto, end)
            while best[0] <= at:
                best.popleft()
            length = best[0] - at
            yield self._clipped(rules.best(at, at), length)
            for p in range(at, at + length):
                reach.pop(p, None)
            at += length

    def _flex_own(self) -> Iterator[Factor]:
        """The chosen phrases are the entries; a candidate counts as one for what follows it."""
        rules = self.rules
        n, at, x = rules.n, 0, 0
        while at < n:
            token = rules.best(at, at)
            most, best = token[1], (0, 0)
            for length in range(most, 0, -1):
                p = at + length
                ahead = rules.best(p, p, (at, length, x + 1))[1] if p < n else 0
                if length + ahead > best[0]:
                    best = (length + ahead, length)
                if best[0] == n - at:  # nothing reaches further than the end
                    break
            found = self._clipped(token, best[1])
            yield found
            x += 1
            rules.lengths.append(found[1])
            rules.add(at, found[1], x)
            at += found[1]

    def _flex_longest(self) -> Iterator[Factor]:
        """The longest factor at each chosen place is an entry; the parse goes on by the chosen length."""
        rules = self.rules
        n, at, x = rules.n, 0, 0
        self.entries = []
        while at < n:
            token = rules.best(at, at)
            self.entries.append(token)
            x += 1
            rules.lengths.append(token[1])
            rules.add(at, token[1], x)
            best = (0, 0)
            for length in range(token[1], 0, -1):
                p = at + length
                ahead = rules.best(p, p)[1] if p < n else 0
                if length + ahead > best[0]:
                    best = (length + ahead, length)
                if best[0] == n - at:
                    break
            yield self._clipped(token, best[1])
            at += best[1]


def count_step(text: Text) -> int:
    """Factor count of `step`, without building tokens."""
    nodes: dict[tuple[int, str | int], int] = {}
    node = z = 0
    for c in text:
        child = nodes.get((node, c))
        if child is None:
            z += 1
            nodes[node, c] = z
            node = 0
        else:
            node = child
    return z + (node > 0)


def count_seeded(text: Text) -> int:
    """Factor count of `seeded`, without building tokens."""
    nodes: dict[tuple[int, str | int], int] = {}
    roots: dict[str | int, int] = {}
    node, z, fresh = 0, 0, 0
    for c in text:
        if not node:
            fresh += 1
            node = roots.setdefault(c, fresh)
            z += 1
            continue
        child = nodes.get((node, c))
        if child is None:
            fresh += 1
            nodes[node, c] = fresh
            fresh += 1
            node = roots.setdefault(c, fresh)
            z += 1
        else:
            node = child
    return z


_NONE: dict = {}


def count_pairs(text: Text, scheme: str) -> tuple[int, int, int, int, int]:
    """(combine, cut, repeat) factor counts of `pair`, `pair_cut` or `pair_run`, and (nodes, split nodes) of the dictionary.

    Without tokens a node needs neither index nor stamp. Where cuts are allowed a factor is no shorter than the first descent went,
    so it becomes an entry where that descent ended.
    """
    n, cuts, powers = len(text), scheme != "pair", scheme == "pair_run"
    label, size, own, kids = [0], [0], [False], [_NONE]
    starts, combine, cut, repeat, at = text.startswith, 0, 0, 0, 0
    extension = extensions.Direct(text) if powers else None

    def leaf(node: int, place: int, length: int) -> None:
        if kids[node] is _NONE:
            kids[node] = {}
        kids[node][text[place]] = len(size)
        label.append(place)
        size.append(length)
        own.append(True)
        kids.append(_NONE)

    def divided(node: int, child: int, same: int) -> int:
        place, middle = label[child], len(size)
        kids[node][text[place]] = middle
        label.append(place)
        size.append(same)
        own.append(False)
        kids.append({text[place + same]: child})
        label[child] = place + same
        size[child] -= same
        return middle

    while at < n:
        # the first descent: longest entry, longest cut, longest power
        node = done = entry = reach = same = child = 0
        first = text[at]
        here = at
        while here < n:
            child = kids[node].get(text[here], 0)
            if not child:
                break
            s = size[child]
            if s > 1:
                place = label[child]
                if not starts(text[place : place + s], here):
                    same = 1 + extensions.first_difference(text, place + 1, here + 1, min(s, n - here) - 1)
                    done += same
                    break
            done += s
            here += s
            node = child
            if own[node]:
                entry = done
                if powers and here < n and text[here] == first:
                    far = done + extension(at, here)
                    if far > reach:
                        reach = far
        # the second part
        length = entry or 1
        begin = at + length
        if begin < n:
            at2, inner, rest, whole = begin, 0, 0, 0
            while at2 < n:
                below = kids[inner].get(text[at2], 0)
                if not below:
                    break
                s = size[below]
                if s > 1:
                    place = label[below]
                    if not starts(text[place : place + s], at2):
                        rest += 1 + extensions.first_difference(text, place + 1, at2 + 1, min(s, n - at2) - 1)
                        break
                rest += s
                at2 += s
                inner = below
                if own[inner]:
                    whole = rest
            length += (rest if cuts else whole) or 1
        kind = 0
        if cuts and done > length:
            length, kind = done, 1
        if powers:
            if at + 1 < n and text[at + 1] == first:
                far = 1 + extension(at, at + 1)
                if far >= reach:
                    reach = far
            if reach > length:
                length, kind = reach, 2
        if kind == 0:
            combine += 1
        elif kind == 1:
            cut += 1
        else:
            repeat += 1
        if length < done:  # only without cuts: the entry ends on the way of the first descent
            node = done = same = 0
            while done < length:
                child = kids[node][text[at + done]]
                s = size[child]
                if s > length - done:
                    same = length - done
                    done = length
                    break
                node, done = child, done + s
        if same:
            node = divided(node, child, same)
        if length > done:
            leaf(node, at + done, length - done)
        else:
            own[node] = True
        at += length
    return combine, cut, repeat, len(size), sum(not x for x in own[1:])
