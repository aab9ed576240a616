"""Ordered sets of attribute values: insert, rank, select and count."""

from __future__ import annotations

from bisect import bisect_left, bisect_right, insort


class SortedArray:
    """A plain sorted list; inserting moves what follows."""

    def __init__(self):
        self.values: list = []

    def __len__(self) -> int:
        return len(self.values)

    def insert(self, value) -> bool:
        """False if the value was there already."""
        if value in self:
            return False
        insort(self.values, value)
        return True

    def fill(self, ordered: list) -> None:
        """Takes values that are in order and distinct, in place of those held."""
        self.values = list(ordered)

    def __contains__(self, value) -> bool:
        i = bisect_left(self.values, value)
        return i < len(self.values) and self.values[i] == value

    def rank(self, value) -> int:
        """How many values are smaller."""
        return bisect_left(self.values, value)

    def select(self, rank: int):
        return self.values[rank]

    def count(self, low, high) -> int:
        return max(0, bisect_right(self.values, high) - bisect_left(self.values, low))


class _Node:
    __slots__ = ("value", "left", "right", "size")

    def __init__(self, value):
        self.value, self.left, self.right, self.size = value, None, None, 1


def _size(x: _Node | None) -> int:
    return x.size if x else 0


def _weight(x: _Node | None) -> int:
    return _size(x) + 1


def _sized(x: _Node) -> _Node:
    x.size = _size(x.left) + _size(x.right) + 1
    return x


class WeightBalancedTree:
    """A search tree whose nodes hold the sizes of their subtrees and keep them within a ratio by rotations."""

    #: No side weighs more than RATIO times the other; a double rotation is due where the inner side weighs TURN times the outer.
    RATIO, TURN = 3, 2

    def __init__(self):
        self.root: _Node | None = None

    def __len__(self) -> int:
        return _size(self.root)

    def __contains__(self, value) -> bool:
        x = self.root
        while x and x.value != value:
            x = x.left if value < x.value else x.right
        return x is not None

    def insert(self, value) -> bool:
        if value in self:
            return False
        path, x = [], self.root
        while x:
            path.append((x, value < x.value))
            x = x.left if value < x.value else x.right
        new = _Node(value)
        for x, went_left in reversed(path):
            if went_left:
                x.left = new
            else:
                x.right = new
            new = self._level(_sized(x))
        self.root = new
        return True

    def _level(self, x: _Node) -> _Node:
        for heavy, light in (("left", "right"), ("right", "left")):
            child = getattr(x, heavy)
            if _weight(child) > self.RATIO * _weight(getattr(x, light)):
                if _weight(getattr(child, light)) >= self.TURN * _weight(getattr(child, heavy)):
                    setattr(x, heavy, self._turn(child, light, heavy))
                return self._turn(x, heavy, light)
        return x

    @staticmethod
    def _turn(x: _Node, heavy: str, light: str) -> _Node:
        """Lifts the child on the heavy side."""
        up = getattr(x, heavy)
        setattr(x, heavy, getattr(up, light))
        setattr(up, light, _sized(x))
        return _sized(up)

    def rank(self, value) -> int:
        below, x = 0, self.root
        while x:
            if x.value < value:
                below += _size(x.left) + 1
                x = x.right
            else:
                x = x.left
        return below

    def select(self, rank: int):
        x = self.root
        while x:
            here = _size(x.left)
            if rank == here:
                return x.value
            if rank < here:
                x = x.left
            else:
                rank, x = rank - here - 1, x.right
        raise IndexError(rank)

    def count(self, low, high) -> int:
        if high < low:
            return 0
        return self.rank(high) + (high in self) - self.rank(low)

    def balanced(self) -> bool:
        """Whether every node keeps the ratio and its size."""
        todo = [self.root] if self.root else []
        while todo:
            x = todo.pop()
            a, b = _weight(x.left), _weight(x.right)
            if max(a, b) > self.RATIO * min(a, b) or x.size != _size(x.left) + _size(x.right) + 1:
                return False
            todo += [y for y in (x.left, x.right) if y]
        return True
