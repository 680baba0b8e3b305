"""Several byte patterns compiled into one minimal deterministic automaton.

The pattern language: literals, ``.``-free classes ``[a-z]``, escapes ``\\xHH`` and ``\\c``,
groups, ``|`` and the repeats ``? + * {m} {m,} {m,n}``. All patterns are over ASCII bytes.
"""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np

_ALL = (1 << 256) - 1


class _Parser:
    """Recursive descent to a nested tuple tree; byte sets are 256-bit integers."""

    def __init__(self, pattern: str):
        self.s, self.i = pattern, 0

    def parse(self):
        tree = self._choice()
        if self.i != len(self.s):
            raise ValueError(f"unexpected {self.s[self.i]!r} at {self.i}")
        return tree

    def _peek(self) -> str:
        return self.s[self.i] if self.i < len(self.s) else ""

    def _take(self) -> str:
        self.i += 1
        return self.s[self.i - 1]

    def _choice(self):
        options = [self._sequence()]
        while self._peek() == "|":
            self._take()
            options.append(self._sequence())
        return ("or", options) if len(options) > 1 else options[0]

    def _sequence(self):
        items = []
        while self._peek() not in ("", "|", ")"):
            items.append(self._repeat(self._atom()))
        return ("cat", items)

    def _repeat(self, atom):
        while (c := self._peek()) and c in "?+*{":
            self._take()
            if c == "{":
                spec = ""
                while (x := self._take()) != "}":
                    spec += x
                low, _, high = spec.partition(",")
                atom = ("rep", atom, int(low), int(low) if "," not in spec else int(high) if high else None)
            else:
                atom = ("rep", atom, int(c == "+"), 1 if c == "?" else None)
        return atom

    def _escape(self) -> int:
        c = self._take()
        if c == "x":
            code = int(self.s[self.i : self.i + 2], 16)
            self.i += 2
            return code
        return ord(c)

    def _atom(self):
        c = self._take()
        if c == "(":
            tree = self._choice()
            if self._take() != ")":
                raise ValueError("missing )")
            return tree
        if c == "[":
            negate, mask = self._peek() == "^" and bool(self._take()), 0
            while (c := self._take()) != "]":
                low = high = self._escape() if c == "\\" else ord(c)
                if self._peek() == "-" and self.s[self.i + 1] != "]":
                    self._take()
                    c = self._take()
                    high = self._escape() if c == "\\" else ord(c)
                mask |= sum(1 << b for b in range(low, high + 1))
            return ("set", _ALL & ~mask if negate else mask)
        return ("set", 1 << (self._escape() if c == "\\" else ord(c)))


def _reverse(tree):
    kind = tree[0]
    if kind == "cat":
        return ("cat", [_reverse(x) for x in tree[1][::-1]])
    if kind == "or":
        return ("or", [_reverse(x) for x in tree[1]])
    return ("rep", _reverse(tree[1]), *tree[2:]) if kind == "rep" else tree


def _shortest(tree):
    """The tree without optional rounds of a repeat at its end: it matches where ``tree`` first does."""
    kind = tree[0]
    if kind == "cat" and tree[1]:
        *head, last = tree[1]
        if head and last[0] == "rep" and not last[2]:
            return _shortest(("cat", head))
        return ("cat", [*head, _shortest(last)])
    if kind == "or":
        return ("or", [_shortest(x) for x in tree[1]])
    if kind == "rep" and tree[2]:
        return ("cat", [tree[1]] * tree[2])
    return tree


class _Nfa:
    def __init__(self):
        self.empty: list[list[int]] = []
        self.moves: list[list[tuple[int, int]]] = []

    def state(self) -> int:
        self.empty.append([])
        self.moves.append([])
        return len(self.empty) - 1

    def add(self, tree, at: int) -> int:
        """Build ``tree`` from state ``at``; returns its last state."""
        kind = tree[0]
        if kind == "set":
            to = self.state()
            self.moves[at].append((tree[1], to))
            return to
        if kind == "cat":
            for x in tree[1]:
                at = self.add(x, at)
            return at
        if kind == "or":
            out = self.state()
            for x in tree[1]:
                start = self.state()
                self.empty[at].append(start)
                self.empty[self.add(x, start)].append(out)
            return out
        _, inner, low, high = tree
        for _ in range(low):
            at = self.add(inner, at)
        if high is None:
            loop, out = self.state(), self.state()
            self.empty[at] += [loop]
            self.empty[self.add(inner, loop)].append(loop)
            self.empty[loop].append(out)
            return out
        out = self.state()
        self.empty[at].append(out)
        for _ in range(high - low):
            at = self.add(inner, at)
            self.empty[at].append(out)
        return out

    def close(self, states: Iterable[int]) -> frozenset[int]:
        seen, todo = set(), list(states)
        while todo:
            s = todo.pop()
            if s not in seen:
                seen.add(s)
                todo += self.empty[s]
        return frozenset(seen)


class Automaton:
    """Minimal deterministic automaton of one or more trees.

    ``classes`` maps a byte to its class, ``table`` holds the next state times the number of
    classes at state times classes plus class, ``accepts`` the set of patterns (as bits) that
    end in a state. States are numbered so that accepting ones are last, from ``first_accept``.
    State ``dead`` (if any) can never accept.
    """

    def __init__(self, trees: list, anywhere: bool):
        nfa = _Nfa()
        root = nfa.state()
        ends = []
        for tree in trees:
            start = nfa.state()
            nfa.empty[root].append(start)
            ends.append(nfa.add(tree, start))
        masks = {m for moves in nfa.moves for m, _ in moves}
        signature = [tuple(m >> b & 1 for m in masks) for b in range(256)]
        number = {s: i for i, s in enumerate(dict.fromkeys(signature))}
        self.classes = bytes(number[s] for s in signature)
        sample = [signature.index(s) for s in number]
        base = nfa.close([root])
        ids, todo, rows = {base: 0}, [base], []
        while todo:
            now = todo.pop(0)
            row = []
            for b in sample:
                to = nfa.close(t for s in now for m, t in nfa.moves[s] if m >> b & 1)
                to = to | base if anywhere else to
                if to not in ids:
                    ids[to] = len(ids)
                    todo.append(to)
                row.append(ids[to])
            rows.append(row)
        table = np.array(rows)
        accept = [sum(1 << i for i, e in enumerate(ends) if e in s) for s in ids]
        # Minimise: refine the partition by what is accepted until successors agree.
        block = np.unique(np.array(accept, dtype=object).astype(str), return_inverse=True)[1]
        while True:
            fine = np.unique(np.column_stack([block, block[table]]), axis=0, return_inverse=True)[1].ravel()
            if fine.max() == block.max():
                break
            block = fine
        n = int(block.max()) + 1
        one = [int(np.flatnonzero(block == k)[0]) for k in range(n)]
        order = sorted(range(n), key=lambda k: (accept[one[k]] > 0, k != block[0], k))
        place = {k: i for i, k in enumerate(order)}
        width = len(sample)
        self.n_states, self.width = n, width
        self.start = place[int(block[0])] * width
        self.table = [place[int(block[t])] * width for k in order for t in table[one[k]]]
        self.accepts = [accept[one[k]] for k in order]
        self.first_accept = next((i for i, a in enumerate(self.accepts) if a), n) * width
        self.dead = next((i * width for i in range(n) if not self.accepts[i] and all(t == i * width for t in self.table[i * width : (i + 1) * width])), -1)

    def scan(self, data: bytes) -> list[tuple[int, int]]:
        """(place after a byte, patterns that end there) in one pass over all bytes."""
        table, first, width = self.table, self.first_accept, self.width
        found, s = [], self.start
        for i, c in enumerate(data.translate(self.classes), 1):
            s = table[s + c]
            if s >= first:
                found.append((i, self.accepts[s // width]))
        return found

    def ends(self, data: bytes | memoryview) -> list[int]:
        """Lengths of the prefixes of ``data`` that match, shortest first; reads until no longer one can."""
        table, s, found = self.table, self.start, []
        classes = self.classes
        for i, b in enumerate(data, 1):
            s = table[s + classes[b]]
            if s == self.dead:
                break
            if s >= self.first_accept:
                found.append(i)
        return found


class PatternSet:
    """All patterns in one automaton, with one forward and one reversed automaton for each.

    The common automaton stops each pattern at its shortest match, which keeps runs of several
    patterns from multiplying its states; the pattern's own automata then find the leftmost
    start and the longest end.
    """

    def __init__(self, patterns: list[str]):
        trees = [_Parser(p).parse() for p in patterns]
        self.any = Automaton([_shortest(t) for t in trees], True)
        self.forward = [Automaton([t], False) for t in trees]
        self.backward = [Automaton([_reverse(t)], False) for t in trees]

    def find(self, data: bytes) -> list[tuple[int, int, int, int]]:
        """(pattern, start, end, end of the shortest match from start): leftmost, longest, non-overlapping for each pattern."""
        out, after = [], [0] * len(self.forward)
        for end, bits in self.any.scan(data):
            while bits:
                k = (bits & -bits).bit_length() - 1
                bits &= bits - 1
                if end <= after[k]:
                    continue
                back = self.backward[k].ends(data[after[k] : end][::-1])
                if back:
                    start = end - back[-1]
                    reach = self.forward[k].ends(memoryview(data)[start:])
                    out.append((k, start, start + reach[-1], start + reach[0]))
                    after[k] = start + reach[-1]
        return out
