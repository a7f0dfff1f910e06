"""Deep-shallow sorting of suffixes: words to a shallow depth, blind tries below. Plain numpy and Python, no Spark."""

from __future__ import annotations

import numpy as np

#: Words of 8 bytes to which suffixes are sorted before the tries take over.
SHALLOW = 3


def words_at(text: np.ndarray) -> np.ndarray:
    """For every place the 8 bytes from there as a big-endian number; zeros follow the end."""
    padded = np.concatenate([text, np.zeros(8, np.uint8)]).astype(np.uint64)
    out = np.zeros(len(text), np.uint64)
    for k in range(8):
        out |= padded[k : k + len(text)] << np.uint64(56 - 8 * k)
    return out


def shallow_groups(words: np.ndarray, places: np.ndarray, depth: int = SHALLOW) -> tuple[np.ndarray, np.ndarray]:
    """Multikey sorting, 8 bytes at a time: (indices into places, group numbers) of the suffixes that share their first 8 * depth bytes with another.

    Each level sorts only what the one before left tied, as quicksort's middle parts are.
    """
    index = np.arange(len(places))
    group = np.zeros(len(places), np.int64)
    for level in range(depth):
        key = words[places[index] + 8 * level]
        order = np.lexsort((key, group))
        index, group, key = index[order], group[order], key[order]
        new = np.concatenate([[True], (group[1:] != group[:-1]) | (key[1:] != key[:-1])]) if len(index) else np.empty(0, bool)
        group = np.cumsum(new) - 1
        tied = np.bincount(group, minlength=1)[group] > 1 if len(index) else new
        index, group = index[tied], group[tied]
    return index, group


class BlindTrie:
    """A binary trie that keeps branching bits alone; one look at a whole key, at the leaf reached, places a new one."""

    def __init__(self, bits: int):
        self.bits, self.root = bits, None

    def add(self, key: int, member: int) -> None:
        if self.root is None:
            self.root = [None, key, [member]]
            return
        node = self.root
        while node[0] is not None:
            node = node[2] if key >> node[0] & 1 else node[1]
        differ = node[1] ^ key
        if not differ:
            node[2].append(member)
            return
        bit = differ.bit_length() - 1
        leaf = [None, key, [member]]
        above, node = None, self.root
        while node[0] is not None and node[0] > bit:
            above, node = node, node[2] if key >> node[0] & 1 else node[1]
        one = key >> bit & 1
        inner = [bit, node, leaf] if one else [bit, leaf, node]
        if above is None:
            self.root = inner
        elif key >> above[0] & 1:
            above[2] = inner
        else:
            above[1] = inner

    def leaves(self) -> list[list[int]]:
        """The members of every leaf, in the order of the keys."""
        out, stack = [], [self.root] if self.root else []
        while stack:
            node = stack.pop()
            if node[0] is None:
                out.append(node[2])
            else:
                stack += [node[2], node[1]]
        return out


def equal_runs(text: np.ndarray, places: np.ndarray, length: int) -> list[list[int]]:
    """The groups of at least two indices into places whose suffixes agree on `length` bytes, in suffix order. Every place must have so many bytes."""
    words = words_at(text)
    index, group = shallow_groups(words, places, min(SHALLOW, length // 8))
    if not len(index):
        return []
    first = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
    size = np.diff(np.append(first, len(group)))
    out: list[tuple[int, list[int]]] = []
    # Two suffixes alone: the trie of two leaves is one comparison, made for all such groups at once.
    pair = first[size == 2]
    same = np.ones(len(pair), bool)
    a, b = places[index[pair]], places[index[pair + 1]]
    for at in [*range(8 * min(SHALLOW, length // 8), length - 7, 8), length - 8]:
        same &= words[a + at] == words[b + at]
    out += [(int(p), index[p : p + 2].tolist()) for p in pair[same]]
    raw = text.tobytes()
    for p, n in zip(first[size > 2].tolist(), size[size > 2].tolist(), strict=True):
        trie = BlindTrie(8 * length)
        for i in index[p : p + n].tolist():
            at = int(places[i])
            trie.add(int.from_bytes(raw[at : at + length], "big"), i)
        out += [(p, leaf) for leaf in trie.leaves() if len(leaf) > 1]
    return [x for _, x in sorted(out, key=lambda x: x[0])]
