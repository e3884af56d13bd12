"""The dictionary of a parse: a radix trie whose edge labels are places in the text.

Every node knows its own entry (0: none) and, of the entries at or below it, the one that ends first. Queries with a gate see only entries
that end at or before it, so a dictionary can be read as it was when the parse stood at an earlier place.
"""

from __future__ import annotations

from bisect import bisect_left

from dictparse.kernels.lce import Text, first_difference

NEVER = 1 << 62


class HashChildren:
    """One hash map for each node that has children."""

    def __init__(self) -> None:
        self.maps: list[dict] = [{}]

    def get(self, node: int, symbol):
        return self.maps[node].get(symbol)

    def put(self, node: int, symbol, child: int) -> None:
        self.maps[node][symbol] = child

    def grow(self) -> None:
        self.maps.append({})


class SortedChildren:
    """Sorted symbols, found by bisection: no hashing, logarithmic in the alphabet."""

    def __init__(self) -> None:
        self.symbols: list[list] = [[]]
        self.nodes: list[list[int]] = [[]]

    def get(self, node: int, symbol):
        own = self.symbols[node]
        k = bisect_left(own, symbol)
        return self.nodes[node][k] if k < len(own) and own[k] == symbol else None

    def put(self, node: int, symbol, child: int) -> None:
        own = self.symbols[node]
        k = bisect_left(own, symbol)
        if k < len(own) and own[k] == symbol:
            self.nodes[node][k] = child
        else:
            own.insert(k, symbol)
            self.nodes[node].insert(k, child)

    def grow(self) -> None:
        self.symbols.append([])
        self.nodes.append([])


class TernaryChildren:
    """A binary search tree of symbols at each node, in order of arrival."""

    def __init__(self) -> None:
        self.roots: list[list | None] = [None]

    def get(self, node: int, symbol):
        at = self.roots[node]
        while at is not None and at[0] != symbol:
            at = at[2] if symbol < at[0] else at[3]
        return at and at[1]

    def put(self, node: int, symbol, child: int) -> None:
        at = self.roots[node]
        if at is None:
            self.roots[node] = [symbol, child, None, None]
            return
        while at[0] != symbol:
            side = 2 if symbol < at[0] else 3
            if at[side] is None:
                at[side] = [symbol, child, None, None]
                return
            at = at[side]
        at[1] = child

    def grow(self) -> None:
        self.roots.append(None)


CHILDREN = {"hash": HashChildren, "sorted": SortedChildren, "ternary": TernaryChildren}


class RadixDictionary:
    def __init__(self, text: Text, children: str = "hash"):
        self.text = text
        self.children = CHILDREN[children]()
        self.get, self.put = self.children.get, self.children.put
        self.label, self.size, self.depth, self.parent = [0], [0], [0], [0]
        self.entry, self.entry_end = [0], [NEVER]
        self.first, self.first_end = [0], [NEVER]  # of the subtree
        self.lookups = self.compared = 0

    def _node(self, parent: int, label: int, size: int, depth: int) -> int:
        self.label.append(label)
        self.size.append(size)
        self.depth.append(depth)
        self.parent.append(parent)
        for column, value in ((self.entry, 0), (self.entry_end, NEVER), (self.first, 0), (self.first_end, NEVER)):
            column.append(value)
        self.children.grow()
        return len(self.size) - 1

    def _stamp(self, node: int, x: int, end: int) -> None:
        if end < self.first_end[node]:
            self.first[node], self.first_end[node] = x, end

    def _own(self, node: int, x: int, end: int) -> None:
        """Makes the node an entry; of equal strings the one that ends first stays."""
        if end < self.entry_end[node]:
            self.entry[node], self.entry_end[node] = x, end

    def insert(self, begin: int, length: int, x: int) -> None:
        """Adds text[begin:begin+length] as entry x."""
        text, end = self.text, begin + length
        node = done = 0
        while done < length:
            symbol = text[begin + done]
            child = self.get(node, symbol)
            if child is None:
                leaf = self._node(node, begin + done, length - done, length)
                self.put(node, symbol, leaf)
                self._own(leaf, x, end)
                self._stamp(leaf, x, end)
                return
            label, size = self.label[child], self.size[child]
            most = min(size, length - done)
            same = most if text[label : label + most] == text[begin + done : begin + done + most] else first_difference(text, label, begin + done, most)
            if same == size:
                node, done = child, done + size
                self._stamp(node, x, end)
                continue
            split = self._node(node, label, same, done + same)
            self.first[split], self.first_end[split] = self.first[child], self.first_end[child]
            self.put(node, symbol, split)
            self.label[child], self.size[child], self.parent[child] = label + same, size - same, split
            self.put(split, text[label + same], child)
            self._stamp(split, x, end)
            node, done = split, done + same
        if length:
            self._own(node, x, end)

    def report(self, node: int) -> int:
        """The index that stands for a node: its own entry's, else that of the entry below it that ends first."""
        return self.entry[node] or self.first[node]

    @property
    def nodes(self) -> int:
        return len(self.size)

    @property
    def split_nodes(self) -> int:
        return sum(not x for x in self.entry[1:])

    def rows(self) -> list[tuple[str, int, int]]:
        """(string, own entry, reported entry) of every node, in string order."""
        names = [""] * len(self.size)
        for node in sorted(range(1, len(self.size)), key=self.depth.__getitem__):
            names[node] = names[self.parent[node]] + str(self.text[self.label[node] : self.label[node] + self.size[node]])
        return sorted((names[k], self.entry[k], self.report(k) if k else 0) for k in range(len(names)))
