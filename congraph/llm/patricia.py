"""A compressed radix tree over byte strings that keeps, for each string, its owner (the least id, null ids last) and a count.

Memory is bounded: past the budget the heaviest subtree moves to a local temporary file, later strings
below it are appended there, and `items` rebuilds one such subtree at a time after the rest is done.
"""

from __future__ import annotations

import pickle
import tempfile
from collections.abc import Iterator

#: Slots of a node: label, children by first byte (None: none), owner (None: a null id), count (0: no string ends here), payload, spill.
LABEL, KIDS, OWNER, COUNT, LOAD, SPILL = range(6)
#: Bytes that a node costs besides its label.
NODE_BYTES = 300


def common_prefix(a: bytes, b: bytes) -> int:
    """Length of the longest common prefix, by halving over memory comparisons."""
    lo, hi = 0, min(len(a), len(b))
    if a[:hi] == b[:hi]:
        return hi
    step = 16
    while step < hi and a[:step] == b[:step]:
        lo, step = step, step * 4
    hi = min(hi, step)
    while hi - lo > 1:
        mid = (lo + hi) // 2
        if a[lo:mid] == b[lo:mid]:
            lo = mid
        else:
            hi = mid
    return hi if a[lo:hi] == b[lo:hi] else lo


class PatriciaTrie:
    def __init__(self, budget: int = 64 << 20, prefix: bytes = b""):
        self.budget, self.prefix, self.used = budget, prefix, 0
        self.root: list = [b"", None, None, 0, None, None]

    def insert(self, key: bytes, owner: int | None, count: int = 1, payload: object = None) -> None:
        node, at = self.root, 0
        while True:
            if node[SPILL] is not None:
                pickle.dump((key[at:], owner, count, payload), node[SPILL])
                return
            if at == len(key):
                break
            kids = node[KIDS]
            child = kids.get(key[at]) if kids else None
            if child is None:
                leaf = [key[at:], None, owner, count, payload, None]
                if kids is None:
                    node[KIDS] = {key[at]: leaf}
                else:
                    kids[key[at]] = leaf
                self.used += NODE_BYTES + len(key) - at
                if self.used > self.budget:
                    self._spill()
                return
            label = child[LABEL]
            if key.startswith(label, at):
                node, at = child, at + len(label)
                continue
            same = common_prefix(label, key[at : at + len(label)])
            upper = [label[:same], {label[same]: child}, None, 0, None, None]
            child[LABEL] = label[same:]
            kids[key[at]] = upper
            self.used += NODE_BYTES
            node, at = upper, at + same
        if node[OWNER] is None or owner is not None and owner < node[OWNER]:
            node[OWNER] = owner
        node[COUNT] += count
        if node[LOAD] is None:
            node[LOAD] = payload

    @staticmethod
    def _weight(node: list) -> int:
        total, stack = 0, [node]
        while stack:
            x = stack.pop()
            total += NODE_BYTES + len(x[LABEL])
            if x[KIDS]:
                stack.extend(x[KIDS].values())
        return total

    def _spill(self) -> None:
        """Moves the heaviest subtree below the first fork to a file."""
        top = self.root
        while top[KIDS] and len(top[KIDS]) == 1 and (only := next(iter(top[KIDS].values())))[KIDS] and only[SPILL] is None:
            top = only
        live = [x for x in (top[KIDS] or {}).values() if x[SPILL] is None]
        if not live:
            return
        heaviest = max(live, key=self._weight)
        out = tempfile.TemporaryFile()
        self.used -= self._weight(heaviest) - NODE_BYTES - len(heaviest[LABEL])
        for key, owner, count, payload in self._walk(heaviest, b""):
            pickle.dump((key, owner, count, payload), out)
        heaviest[KIDS], heaviest[OWNER], heaviest[COUNT], heaviest[LOAD], heaviest[SPILL] = None, None, 0, None, out

    @staticmethod
    def _walk(top: list, above: bytes) -> Iterator[tuple[bytes, int | None, int, object]]:
        """Strings below a node that holds no spilled part; the node's own label is left out."""
        stack = [(top, above)]
        while stack:
            node, path = stack.pop()
            if node[COUNT]:
                yield path, node[OWNER], node[COUNT], node[LOAD]
            for child in (node[KIDS] or {}).values():
                if child[SPILL] is not None:
                    child[SPILL].seek(0)
                    while True:
                        try:
                            key, owner, count, payload = pickle.load(child[SPILL])
                        except EOFError:
                            break
                        yield path + child[LABEL] + key, owner, count, payload
                    child[SPILL].close()
                else:
                    stack.append((child, path + child[LABEL]))

    def items(self) -> Iterator[tuple[bytes, int | None, int, object]]:
        """(string, owner, count, payload), each string once; empties the tree."""
        stack, spilled = [(self.root, self.prefix)], []
        while stack:
            node, path = stack.pop()
            if node[SPILL] is not None:
                spilled.append((path, node[SPILL]))
                continue
            if node[COUNT]:
                yield path, node[OWNER], node[COUNT], node[LOAD]
            stack.extend((child, path + child[LABEL]) for child in (node[KIDS] or {}).values())
        self.root, self.used = [b"", None, None, 0, None, None], 0
        for path, file in spilled:
            part = PatriciaTrie(self.budget, path)
            file.seek(0)
            while True:
                try:
                    part.insert(*pickle.load(file))
                except EOFError:
                    break
            file.close()
            yield from part.items()
