"""Searches of a dictionary for what can begin at a place of the text.

`gate` hides entries that end after it. `extra` is a phrase (begin, length, index) that counts as an entry although it isn't inserted.
All lengths are 0 if nothing fits.
"""

from __future__ import annotations

from collections.abc import Iterator

from dictparse.kernels.lce import first_difference
from dictparse.kernels.trie import NEVER, RadixDictionary

Extra = tuple[int, int, int] | None


def walk(trie: RadixDictionary, at: int, gate: int = NEVER, lce=None) -> tuple[int, int, int, int, int, int]:
    """One descent: (entry, its length, cut entry, cut length, power base, power length).

    The entry is the longest whole one, the cut the longest prefix of any, and with `lce` the power the longest (cut) power of a whole one.
    """
    text, get = trie.text, trie.get
    n = len(text)
    entry = entry_size = cut = cut_size = base = power_size = 0
    node = done = 0
    while at + done < n:
        child = get(node, text[at + done])
        trie.lookups += 1
        if child is None or trie.first_end[child] > gate:
            break
        label, size = trie.label[child], trie.size[child]
        most = min(size, n - at - done)
        same = most if text[label : label + most] == text[at + done : at + done + most] else first_difference(text, label, at + done, most)
        trie.compared += same
        done += same
        if same < size:
            cut, cut_size = trie.first[child], done
            break
        node = child
        if trie.entry[node] and trie.entry_end[node] <= gate:
            entry, entry_size = trie.entry[node], done
            cut = entry
            if lce is not None:
                # most entries aren't followed by their own first symbol
                reach = done + lce(at, at + done) if at + done < n and text[at] == text[at + done] else done
                if reach > power_size:
                    base, power_size = entry, reach
        else:
            cut = trie.first[node]
        cut_size = done
    return entry, entry_size, cut, cut_size, base, power_size


def _edges(trie: RadixDictionary, at: int, gate: int) -> Iterator[tuple[int, int, bool]]:
    """One descent by itself: (node, symbols matched, whether its edge matched whole) of every edge taken."""
    text = trie.text
    n, node, done = len(text), 0, 0
    while at + done < n:
        child = trie.get(node, text[at + done])
        trie.lookups += 1
        if child is None or trie.first_end[child] > gate:
            return
        size = trie.size[child]
        same = first_difference(text, trie.label[child], at + done, min(size, n - at - done))
        trie.compared += same
        done += same
        yield child, done, same == size
        if same < size:
            return
        node = child


def longest_entry(trie: RadixDictionary, at: int, gate: int = NEVER) -> tuple[int, int]:
    """(entry, length) of the longest whole entry, else nothing."""
    best = (0, 0)
    for node, done, whole in _edges(trie, at, gate):
        if whole and trie.entry[node] and trie.entry_end[node] <= gate:
            best = (trie.entry[node], done)
    return best


def longest_cut(trie: RadixDictionary, at: int, gate: int = NEVER) -> tuple[int, int]:
    """(entry, length) of the longest prefix of any entry."""
    best = (0, 0)
    for node, done, whole in _edges(trie, at, gate):
        own = whole and trie.entry[node] and trie.entry_end[node] <= gate
        best = (trie.entry[node] if own else trie.first[node], done)
    return best


def longest_power(trie: RadixDictionary, at: int, lce, gate: int = NEVER) -> tuple[int, int]:
    """(entry, length) of the longest (cut) power of a whole entry."""
    best = (0, 0)
    for node, done, whole in _edges(trie, at, gate):
        if whole and trie.entry[node] and trie.entry_end[node] <= gate:
            reach = done + lce(at, at + done)
            if reach > best[1]:
                best = (trie.entry[node], reach)
    return best


def separate_first(trie: RadixDictionary, at: int, gate: int, lce, extra: Extra = None) -> tuple[int, int, int, int, int, int]:
    """What fused_first() finds, by a descent for each of the three roles."""
    found = (*longest_entry(trie, at, gate), *longest_cut(trie, at, gate), *(longest_power(trie, at, lce, gate) if lce else (0, 0)))
    return _with_extra(trie, at, lce, extra, found)


def with_symbol(trie: RadixDictionary, at: int, lce, base: int, size: int) -> tuple[int, int]:
    if at + 1 < len(trie.text) and trie.text[at] == trie.text[at + 1]:
        run = 1 + lce(at, at + 1)
        if run >= size:
            return 0, run
    return base, size


def fused_first(trie: RadixDictionary, at: int, gate: int, lce, extra: Extra = None) -> tuple[int, int, int, int, int, int]:
    """walk(), with an extra phrase taken into account in all three roles."""
    found = walk(trie, at, gate, lce)
    return _with_extra(trie, at, lce, extra, found) if extra else found


def _with_extra(trie: RadixDictionary, at: int, lce, extra: Extra, found: tuple[int, int, int, int, int, int]) -> tuple[int, int, int, int, int, int]:
    if not extra:
        return found
    entry, entry_size, cut, cut_size, base, power_size = found
    begin, length, x = extra
    same = first_difference(trie.text, begin, at, min(length, len(trie.text) - at))
    if same == length:
        if length > entry_size:
            entry, entry_size = x, length
        if lce is not None:
            reach = length + lce(at, at + length)
            if reach > power_size:
                base, power_size = x, reach
    if same > cut_size:
        cut, cut_size = x, same
    return entry, entry_size, cut, cut_size, base, power_size


def fused_second(trie: RadixDictionary, at: int, gate: int, cuts: bool, extra: Extra = None) -> tuple[int, int]:
    """The second part: the longest cut, or the longest whole entry if cuts aren't allowed."""
    entry, entry_size, cut, cut_size, _, _ = fused_first(trie, at, gate, None, extra)
    return (cut, cut_size) if cuts else (entry, entry_size)
