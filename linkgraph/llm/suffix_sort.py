"""Deep-shallow sorting of byte strings.

Strings are partitioned by multikey quicksort down to a shallow depth; groups
that still agree there are likely to agree for long, so each is ordered by a
blind trie, which looks at one byte per branching node on the way down and
compares one pair of strings per insertion.
"""

from __future__ import annotations

import random

SHALLOW = 16


def common_prefix(a: bytes, b: bytes) -> int:
    n = min(len(a), len(b))
    if a[:n] == b[:n]:
        return n
    differ = int.from_bytes(a[:n], "big") ^ int.from_bytes(b[:n], "big")
    return n - 1 - (differ.bit_length() - 1) // 8


class _Node:
    __slots__ = ("depth", "moves", "some")

    def __init__(self, depth: int, moves: dict, some: int):
        #: moves: next byte (-1 at a string's end) to a node or a list of equal strings.
        self.depth, self.moves, self.some = depth, moves, some


def blind_trie(strings: list[bytes], group: list[int]) -> tuple[list[int], list[int]]:
    """Order of ``group`` and the common prefix of each with the one before."""
    byte = lambda s, d: s[d] if d < len(s) else -1
    first = group[0]
    root = _Node(len(strings[first]), {-1: [first]}, first)
    for i in group[1:]:
        s = strings[i]
        node = root
        while isinstance(node, _Node):  # blind descent to any string below
            nxt = node.moves.get(byte(s, node.depth))
            if nxt is None:
                break
            node = nxt
        other = node.some if isinstance(node, _Node) else node[0]
        lcp = common_prefix(s, strings[other])
        parent, key, node = None, None, root
        while isinstance(node, _Node) and node.depth < lcp:
            parent, key = node, byte(s, node.depth)
            node = node.moves.get(key)
        if isinstance(node, _Node) and node.depth == lcp:
            mine = byte(s, lcp)
            if mine in node.moves:
                held = node.moves[mine]
                held.append(i)  # equal strings share a leaf
            else:
                node.moves[mine] = [i]
        elif node is None:
            parent.moves[key] = [i]
        elif isinstance(node, list) and lcp == len(s) == len(strings[node[0]]):
            node.append(i)
        else:
            split = _Node(lcp, {byte(strings[other], lcp): node, byte(s, lcp): [i]}, other)
            if parent is None:
                root = split
            else:
                parent.moves[key] = split
    order: list[int] = []
    lcps: list[int] = []
    stack: list[tuple[object, int]] = [(root, 0)]
    while stack:
        node, above = stack.pop()
        if isinstance(node, list):
            for k, i in enumerate(node):
                lcps.append(above if k == 0 else len(strings[i]))
                order.append(i)
        else:
            keys = sorted(node.moves)
            for k in range(len(keys) - 1, 0, -1):
                stack.append((node.moves[keys[k]], node.depth))
            stack.append((node.moves[keys[0]], above))
    return order, lcps


def deep_shallow(strings: list[bytes], shallow: int = SHALLOW) -> tuple[list[int], list[int]]:
    """Order of the strings and each one's common prefix with the one before."""
    pick = random.Random(len(strings))
    order: list[int] = []
    lcps: list[int] = []
    stack: list[tuple[list[int], int, int]] = [([*range(len(strings))], 0, 0)] if strings else []
    while stack:
        group, depth, above = stack.pop()
        if len(group) == 1:
            order.append(group[0])
            lcps.append(above)
            continue
        if depth >= shallow:
            part, part_lcps = blind_trie(strings, group)
            order += part
            lcps += [above, *part_lcps[1:]]
            continue
        letter = {i: strings[i][depth] if depth < len(strings[i]) else -1 for i in group}
        pivot = letter[group[pick.randrange(len(group))]]
        less = [i for i in group if letter[i] < pivot]
        same = [i for i in group if letter[i] == pivot]
        more = [i for i in group if letter[i] > pivot]
        if more:
            stack.append((more, depth, depth))
        if pivot < 0:  # strings that end here are equal
            if less:
                stack.append((less, depth, above))
            for k, i in enumerate(same):
                order.append(i)
                lcps.append((depth if less else above) if k == 0 else depth)
            continue
        stack.append((same, depth + 1, depth if less else above))
        if less:
            stack.append((less, depth, above))
    return order, lcps
