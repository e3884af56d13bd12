"""The parses of `kernels.parse` with the default options, faster: the same factors from one function for each family.

A greedy parse inserts an entry where its descent ended, and as entries end in the order of their indexes, the entry that made a node is
the one below it that ends first. So nothing is stamped on the way down. `kernels.parse` stays the reference; tests compare the two.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Callable

from dictparse.kernels.lce import Direct, first_difference
from dictparse.kernels.parse import LOOKAHEADS, SCHEMES, Factor, clip
from dictparse.kernels.trie import NEVER

_NONE: dict = {}
#: Edges up to this length are compared symbol by symbol.
_SHORT = 12


def _same(text: str, i: int, j: int, most: int) -> int:
    """first_difference() for two places whose first symbols agree."""
    if most > _SHORT:
        return first_difference(text, i, j, most)
    k = 1
    while k < most and text[i + k] == text[j + k]:
        k += 1
    return k


class Dictionary:
    """The columns of a radix trie, by node: edge label and size, own entry and its end, the entry below that ends first and its end, children."""

    def __init__(self, text: str):
        self.text = text
        self.label, self.size, self.own, self.own_end, self.first, self.first_end, self.kids = [0], [0], [0], [NEVER], [0], [NEVER], [_NONE]

    def leaf(self, node: int, place: int, length: int, x: int, end: int) -> None:
        if self.kids[node] is _NONE:
            self.kids[node] = {}
        self.kids[node][self.text[place]] = len(self.size)
        self.label.append(place)
        self.size.append(length)
        self.own.append(x)
        self.own_end.append(end)
        self.first.append(x)
        self.first_end.append(end)
        self.kids.append(_NONE)

    def divided(self, node: int, child: int, same: int) -> int:
        """The new node on the edge to a child, so many symbols down."""
        place, middle = self.label[child], len(self.size)
        self.kids[node][self.text[place]] = middle
        self.label.append(place)
        self.size.append(same)
        self.own.append(0)
        self.own_end.append(NEVER)
        self.first.append(self.first[child])
        self.first_end.append(self.first_end[child])
        self.kids.append({self.text[place + same]: child})
        self.label[child] = place + same
        self.size[child] -= same
        return middle

    def insert(self, begin: int, length: int, x: int) -> None:
        """Adds text[begin:begin+length] as entry x; entries may end in any order."""
        text, end, node, done = self.text, begin + length, 0, 0
        while done < length:
            child = self.kids[node].get(text[begin + done])
            if child is None:
                self.leaf(node, begin + done, length - done, x, end)
                return
            size = self.size[child]
            same = _same(text, self.label[child], begin + done, min(size, length - done))
            node = child if same == size else self.divided(node, child, same)
            done += same
            if end < self.first_end[node]:
                self.first[node], self.first_end[node] = x, end
        if end < self.own_end[node]:
            self.own[node], self.own_end[node] = x, end


def _greedy(text: str, scheme: str) -> tuple[list[Factor], Dictionary]:
    """Factors and dictionary of the pair schemes and step_run."""
    n, pairs, cuts, powers = len(text), scheme != "step_run", scheme != "pair", scheme in ("pair_run", "step_run")
    d = Dictionary(text)
    label, size, own, own_end, firsts, kids, leaf = d.label, d.size, d.own, d.own_end, d.first, d.kids, d.leaf
    starts, extension, out, lengths, at, x = text.startswith, Direct(text), [], [0], 0, 0
    while at < n:
        x += 1
        node = done = entry = entry_size = reach = base = same = child = cut = 0
        first, here = text[at], at
        while here < n:
            child = kids[node].get(text[here])
            if child is None:
                break
            s = size[child]
            if s > 1:
                place = label[child]
                if not starts(text[place : place + s], here):
                    same = _same(text, place, here, min(s, n - here))
                    done += same
                    cut = firsts[child]
                    break
            done += s
            here += s
            node = child
            cut = own[node]
            if cut:
                entry, entry_size = cut, done
                if powers and here < n and text[here] == first:
                    far = done + extension(at, here)
                    if far > reach:
                        base, reach = entry, far
            else:
                cut = firsts[node]
        if pairs:
            if entry_size > 1:
                length, ref1, sym1 = entry_size, entry, None
            else:
                length, ref1, sym1 = 1, None, first
            begin = at + length
            if begin == n:
                ref2, sym2 = 0, None
            else:
                at2, inner, rest, whole, second = begin, 0, 0, 0, 0
                while at2 < n:
                    below = kids[inner].get(text[at2])
                    if below is None:
                        break
                    s = size[below]
                    if s > 1:
                        place = label[below]
                        if not starts(text[place : place + s], at2):
                            if cuts:
                                rest += _same(text, place, at2, min(s, n - at2))
                                second = firsts[below]
                            break
                    rest += s
                    at2 += s
                    inner = below
                    if own[inner]:
                        whole, second = rest, own[inner]
                    elif cuts:
                        second = firsts[inner]
                if not cuts:
                    rest = whole
                if rest > 1:
                    ref2, sym2 = second, None
                    length += rest
                else:
                    ref2, sym2 = None, text[begin]
                    length += 1
            if cuts and done > length:
                length = done
                found = (at, done, "cut", cut, None, None, None, 1)
            else:
                found = (at, length, "combine", ref1, sym1, ref2, sym2, None)
        else:
            if at + entry_size == n:
                length = entry_size
                found = (at, length, "entry", entry, None, None, None, None)
            else:
                length = entry_size + 1
                found = (at, length, "extend", entry, None, None, text[at + entry_size], None)
            if done > length:
                length = done
                found = (at, done, "cut", cut, None, None, None, 1)
        if powers:
            if at + 1 < n and text[at + 1] == first:
                far = 1 + extension(at, at + 1)
                if far >= reach:
                    base, reach = 0, far
            if reach > length:
                length = reach
                found = (at, length, "repeat", base or None, None if base else first, None, None, -(-length // (lengths[base] if base else 1)))
        out.append(found)
        lengths.append(length)
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
            node = d.divided(node, child, same)
        if length > done:
            leaf(node, at + done, length - done, x, at + length)
        elif not own[node]:
            own[node], own_end[node] = x, at + length
        at += length
    return out, d


def _step(text: str) -> list[Factor]:
    nodes: dict[tuple[int, str], int] = {}
    out: list[Factor] = []
    node = begin = 0
    get = nodes.get
    for here, c in enumerate(text):
        child = get((node, c))
        if child is None:
            out.append((begin, here + 1 - begin, "extend", node, None, None, c, None))
            nodes[node, c] = len(out)
            node, begin = 0, here + 1
        else:
            node = child
    if node:
        out.append((begin, len(text) - begin, "entry", node, None, None, None, None))
    return out


def _seeded(text: str) -> list[Factor]:
    """An entry is a factor and the symbol after it, so a factor's descent ends where its entry begins to be new."""
    nodes: dict[tuple[int | str, str], int] = {}
    out: list[Factor] = []
    get, node, begin = nodes.get, None, 0
    for here, c in enumerate(text):
        if node is None:
            node = c
            continue
        child = get((node, c))
        if child is None:
            out.append((begin, here - begin, "entry", None, node, None, None, None) if here - begin == 1 else (begin, here - begin, "entry", node, None, None, None, None))
            nodes[node, c] = len(out)
            node, begin = c, here
        else:
            node = child
    if node is not None:
        size = len(text) - begin
        out.append((begin, size, "entry", None, node, None, None, None) if size == 1 else (begin, size, "entry", node, None, None, None, None))
    return out


def _searches(text: str, scheme: str, d: Dictionary, lengths: list[int]) -> tuple[Callable[..., int], Callable[[int], Factor]]:
    """Two functions of a place: the length of the greedy factor there, and the factor, with the dictionary as the parse had it there.

    The first may be given a phrase (begin, length) that counts as an entry.
    """
    label, size, own, own_end, firsts, first_end, kids = d.label, d.size, d.own, d.own_end, d.first, d.first_end, d.kids
    n, slack, powers, starts, extension = len(text), int(scheme == "seeded"), scheme == "pair_run", text.startswith, Direct(text)

    def measure(p: int, begin: int = 0, extra: int = 0) -> int:
        gate = p + slack
        node = done = whole = reach = 0
        here, first = p, text[p]
        while here < n:
            child = kids[node].get(text[here])
            if child is None or first_end[child] > gate:
                break
            s = size[child]
            if s > 1:
                place = label[child]
                if not starts(text[place : place + s], here):
                    done += _same(text, place, here, min(s, n - here))
                    break
            done += s
            here += s
            node = child
            if own_end[node] <= gate:
                whole = done
                if powers and here < n and text[here] == first:
                    far = done + extension(p, here)
                    if far > reach:
                        reach = far
        if extra and text[begin] == first:
            same = _same(text, begin, p, min(extra, n - p))
            if same == extra:
                if extra > whole:
                    whole = extra
                if powers:
                    far = extra + extension(p, p + extra)
                    if far > reach:
                        reach = far
            if same > done:
                done = same
        length = whole or 1
        if slack:
            return length
        here = second = p + length
        if here < n:
            node = rest = 0
            while here < n:
                child = kids[node].get(text[here])
                if child is None or first_end[child] > gate:
                    break
                s = size[child]
                if s > 1:
                    place = label[child]
                    if not starts(text[place : place + s], here):
                        rest += _same(text, place, here, min(s, n - here))
                        break
                rest += s
                here += s
                node = child
            if extra and text[begin] == text[second]:
                same = _same(text, begin, second, min(extra, n - second))
                if same > rest:
                    rest = same
            length += rest or 1
        if done > length:
            length = done
        if powers and p + 1 < n and text[p + 1] == first:
            far = 1 + extension(p, p + 1)
            if far > reach:
                reach = far
        return reach if reach > length else length

    def descent(p: int, gate: int) -> tuple[int, int, int, int, int, int]:
        node = done = entry = entry_size = cut = base = reach = 0
        here, first = p, text[p]
        while here < n:
            child = kids[node].get(text[here])
            if child is None or first_end[child] > gate:
                break
            s = size[child]
            if s > 1:
                place = label[child]
                if not starts(text[place : place + s], here):
                    done += _same(text, place, here, min(s, n - here))
                    cut = firsts[child]
                    break
            done += s
            here += s
            node = child
            if own_end[node] <= gate:
                cut = entry = own[node]
                entry_size = done
                if powers and here < n and text[here] == first:
                    far = done + extension(p, here)
                    if far > reach:
                        base, reach = entry, far
            else:
                cut = firsts[node]
        return entry, entry_size, cut, done, base, reach

    def token(p: int) -> Factor:
        entry, entry_size, cut, done, base, reach = descent(p, p + slack)
        if slack:
            return (p, entry_size, "entry", entry, None, None, None, None) if entry_size > 1 else (p, 1, "entry", None, text[p], None, None, None)
        length, ref1, sym1 = (entry_size, entry, None) if entry_size > 1 else (1, None, text[p])
        begin = p + length
        if begin == n:
            ref2, sym2 = 0, None
        else:
            _, _, second, rest, _, _ = descent(begin, p)
            ref2, sym2, rest = (second, None, rest) if rest > 1 else (None, text[begin], 1)
            length += rest
        found = (p, done, "cut", cut, None, None, None, 1) if done > length else (p, length, "combine", ref1, sym1, ref2, sym2, None)
        length = found[1]
        if powers:
            if p + 1 < n and text[p + 1] == text[p]:
                far = 1 + extension(p, p + 1)
                if far >= reach:
                    base, reach = 0, far
            if reach > length:
                found = (p, reach, "repeat", base or None, None if base else text[p], None, None, -(-reach // (lengths[base] if base else 1)))
        return found

    return measure, token


def _clipped(token: Factor, length: int, lengths: list[int]) -> Factor:
    return clip(token, length, lengths[token[3]] if token[2] == "repeat" and token[3] else 1)


def _flex_fixed(text: str, scheme: str) -> tuple[list[Factor], list[Factor], Dictionary]:
    n = len(text)
    if scheme == "seeded":
        entries, d = _seeded(text), Dictionary(text)
        for x, (begin, length, *_) in enumerate(entries, 1):
            if begin + length < n:
                d.insert(begin, length + 1, x)
    else:
        entries, d = _greedy(text, scheme)
    lengths = [0, *(e[1] for e in entries)]
    measure, token = _searches(text, scheme, d, lengths)
    out: list[Factor] = []
    best: deque[tuple[int, int]] = deque()  # (place, where its factor ends), those that end furthest
    at = upto = 0
    ends = 0 if not n else measure(0)
    while at < n:
        # places up to where the current factor ends; a place beyond the text ends there
        for p in range(max(upto, at) + 1, ends + 1):
            far = p + measure(p) if p < n else n
            while best and best[-1][1] <= far:  # of equal ones the longer factor
                best.pop()
            best.append((p, far))
        upto = max(upto, ends)
        while best[0][0] <= at:
            best.popleft()
        to, ends = best[0]
        out.append(_clipped(token(at), to - at, lengths))
        at = to
    return out, entries, d


def _stepwise(text: str, scheme: str, lookahead: str) -> tuple[list[Factor], list[Factor] | None, Dictionary]:
    n, d, lengths, own = len(text), Dictionary(text), [0], lookahead == "flex_own"
    measure, token = _searches(text, scheme, d, lengths)
    slack, out, entries, at, x = int(scheme == "seeded"), [], [], 0, 0
    while at < n:
        longest = token(at)
        most = longest[1]
        x += 1
        if not own:
            entries.append(longest)
            lengths.append(most)
            if at + most + slack <= n:
                d.insert(at, most + slack, x)
        furthest = chosen = 0
        for length in range(most, 0, -1):
            p = at + length
            far = length + (0 if p >= n else measure(p, at, length) if own else measure(p))
            if far > furthest:
                furthest, chosen = far, length
            if furthest == n - at:  # nothing reaches further than the end
                break
        found = _clipped(longest, chosen, lengths)
        out.append(found)
        if own:
            lengths.append(chosen)
            d.insert(at, chosen, x)
        at += chosen
    return out, None if own else entries, d


def knows(scheme: str, lookahead: str) -> bool:
    """Whether parsed() has this parse."""
    return scheme in SCHEMES and (lookahead == "none" or lookahead in LOOKAHEADS and (scheme in ("pair_cut", "pair_run") or scheme == "seeded" and lookahead != "flex_own"))


def _ahead(text: str, scheme: str, lookahead: str) -> tuple[list[Factor], list[Factor] | None, Dictionary]:
    return _flex_fixed(text, scheme) if lookahead == "flex_fixed" else _stepwise(text, scheme, lookahead)


def parsed(text: str, scheme: str, lookahead: str = "none") -> tuple[list[Factor], list[Factor] | None]:
    """Phrases and, where these aren't the phrases, entries: those of Parse(text, scheme, lookahead)."""
    if not knows(scheme, lookahead):
        raise ValueError(f"no quick parse {scheme}/{lookahead}")
    if lookahead != "none":
        return _ahead(text, scheme, lookahead)[:2]
    return (_step(text) if scheme == "step" else _seeded(text) if scheme == "seeded" else _greedy(text, scheme)[0]), None


def count_ahead(text: str, scheme: str, lookahead: str) -> tuple[int, int, int, int, int, int]:
    """Factors of a look-ahead parse, those of the kinds combine, cut and repeat, nodes and split nodes of the dictionary."""
    phrases, _, d = _ahead(text, scheme, lookahead)
    kinds = [f[2] for f in phrases]
    return len(kinds), *(kinds.count(k) for k in ("combine", "cut", "repeat")), len(d.size), sum(not x for x in d.own[1:])
