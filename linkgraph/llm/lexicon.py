"""A minimal acyclic transducer over byte strings, stored as one flat file.

Words are added in byte order; states with equal right languages are shared, so
the automaton is the smallest one.  Every transition carries how many words
precede its target, so that the sum along a path is the word's rank, and the
rank leads to the word's output: a short run of integers.  The file is opened
with ``mmap``; a lookup touches only the pages on its path, and all workers of
a machine share them.
"""

from __future__ import annotations

import array
import mmap
import struct
from collections.abc import Iterable, Sequence

_MAGIC = b"MAT1"


def compile_lexicon(entries: Iterable[tuple[bytes, Sequence[int]]]) -> bytes:
    """The file image of a transducer from distinct words to integer runs."""
    pairs = sorted((bytes(w), tuple(out)) for w, out in entries)
    for (a, _), (b, _) in zip(pairs, pairs[1:], strict=False):
        if a == b:
            raise ValueError(f"repeated word {a!r}")
    registry: dict[tuple, int] = {}
    frozen: list[tuple[bool, tuple[tuple[int, int], ...]]] = []

    def freeze(node: list) -> int:
        key = (node[0], tuple(node[1]))
        found = registry.get(key)
        if found is None:
            found = registry[key] = len(frozen)
            frozen.append(key)
        return found

    # open path from the root: each node is [final, [(label, frozen target)...]]
    path: list[list] = [[False, []]]
    labels: list[int] = []
    for word, _ in pairs:
        common = 0
        while common < len(labels) and common < len(word) and labels[common] == word[common]:
            common += 1
        while len(labels) > common:
            done = freeze(path.pop())
            path[-1][1].append((labels.pop(), done))
        for byte in word[common:]:
            labels.append(byte)
            path.append([False, []])
        path[-1][0] = True
    while labels:
        done = freeze(path.pop())
        path[-1][1].append((labels.pop(), done))
    root = freeze(path[0])

    # targets are frozen before their sources, so one pass counts the words below
    below = [0] * len(frozen)
    first = array.array("I")
    final = bytearray()
    label = bytearray()
    target, skip = array.array("I"), array.array("I")
    for state, (is_final, moves) in enumerate(frozen):
        first.append(len(label))
        final.append(is_final)
        count = int(is_final)
        for byte, to in moves:
            label.append(byte)
            target.append(to)
            skip.append(count)
            count += below[to]
        below[state] = count
    first.append(len(label))
    starts, outputs = array.array("I", [0]), array.array("I")
    for _, out in pairs:
        outputs.extend(out)
        starts.append(len(outputs))
    pad = lambda raw: raw + b"\0" * (-len(raw) % 4)
    parts = [pad(bytes(final)), pad(bytes(label)), first.tobytes(), target.tobytes(), skip.tobytes(), starts.tobytes(), outputs.tobytes()]
    head = _MAGIC + struct.pack("<5I", root, len(frozen), len(label), len(pairs), len(outputs))
    return head + b"".join(parts)


class Lexicon:
    """Read-only view of a compiled transducer in a file."""

    def __init__(self, path: str):
        with open(path, "rb") as f:
            self._map = mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ)
        if self._map[:4] != _MAGIC:
            raise ValueError(f"{path} is no lexicon")
        self.root, self.n_states, self.n_moves, self.n_words, n_out = struct.unpack("<5I", self._map[4:24])
        at = 24
        up = lambda n: n + (-n % 4)
        self._final, at = at, at + up(self.n_states)
        self._label, at = at, at + up(self.n_moves)
        whole = memoryview(self._map)

        def ints(n: int) -> memoryview:
            nonlocal at
            view = whole[at : at + 4 * n].cast("I")
            at += 4 * n
            return view

        self._first, self._target, self._skip = ints(self.n_states + 1), ints(self.n_moves), ints(self.n_moves)
        self._starts, self._out = ints(self.n_words + 1), ints(n_out)

    def rank(self, word: bytes) -> int:
        """Place of the word among all, or -1."""
        state, rank, base = self.root, 0, self._label
        first, target, skip, find = self._first, self._target, self._skip, self._map.find
        for i in range(len(word)):
            move = find(word[i : i + 1], base + first[state], base + first[state + 1]) - base
            if move < 0:
                return -1
            rank += skip[move]
            state = target[move]
        return rank if self._map[self._final + state] else -1

    def get(self, word: bytes) -> tuple[int, ...] | None:
        rank = self.rank(word)
        return None if rank < 0 else tuple(self._out[self._starts[rank] : self._starts[rank + 1]])
