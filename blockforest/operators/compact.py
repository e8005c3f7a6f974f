"""A block's rows column by column, each column in the smallest form that gives its values back."""

from __future__ import annotations

import pickle

import numpy as np
import pyarrow as pa

from .tree import Tree

#: Rows of a piece, and the most rows that a block keeps as one dense matrix.
PIECE = 1 << 18
#: Ends of a tree that are met by bits, and a row's bits before it met any node.
_LEAVES = 64
_ALL = np.uint64(0xFFFFFFFFFFFFFFFF)
_LOWEST = {np.dtype(np.uint8): 0, np.dtype(np.int32): -(2**31)}
#: Rows whose bits are met at once.
_STRIP = 1 << 14


def _list(column) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 0))


def parts_of(column) -> tuple[np.ndarray, np.ndarray, int]:
    """(numbers, places of ones, how many places) of a features column, be it lists of doubles or ``features.compact`` rows."""
    if not pa.types.is_struct(column.type):
        return _list(column), np.zeros((len(column), 0), np.int16), 0
    width = column.field("width").to_numpy()
    return _list(column.field("numbers")), _list(column.field("ones")).astype(np.int16), int(width[0]) if len(width) else 0


def column_pieces(batches, features: int = 1):
    """(piece, record batches in it) of compact rows, ``PIECE`` rows or a little more at a time."""
    held, n = [], 0
    for batch in batches:
        held, n = [*held, batch], n + batch.num_rows
        if n >= PIECE:
            yield _piece_of(held, features), held
            held, n = [], 0
    if n:
        yield _piece_of(held, features), held


def _piece_of(batches, features: int) -> _Piece:
    parts = [parts_of(b.column(features)) for b in batches if b.num_rows]
    return _Piece(np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts]))


def pack_rows(batches):
    """One binary for up to ``PIECE`` rows or a little more of ``(row_id, features, label)``: a block that several tasks read."""
    for piece, held in column_pieces(batches):
        ids, labels = (np.concatenate([b.column(k).to_numpy() for b in held]) for k in (0, 2))
        width = next(parts_of(b.column(1))[2] for b in held if b.num_rows)
        packed = pickle.dumps((ids.astype(np.int64), labels.astype(np.int16), piece, width), protocol=5)
        yield pa.RecordBatch.from_arrays([pa.array([packed], pa.binary())], names=["rows"])


def dense(numbers: np.ndarray, ones: np.ndarray, width: int) -> np.ndarray:
    """The matrix: numbers first, then a 0/1 column for every place."""
    if not width:
        return numbers
    out = np.zeros((len(numbers), numbers.shape[1] + width))
    out[:, : numbers.shape[1]] = numbers
    row, k = np.nonzero(ones >= 0)
    out[row, numbers.shape[1] + ones[row, k]] = 1.0
    return out


class _Column:
    """Codes of at most 256 values, whole hundredths, or the doubles themselves."""

    def __init__(self, values: np.ndarray):
        self.kind, self.data, self.values = "plain", values.copy(), None
        known = np.unique(values[:: max(1, len(values) // 4096)])
        if len(known) <= 256 and (known[(codes := np.searchsorted(known, values).clip(max=len(known) - 1))] == values).all():
            self.kind, self.data, self.values = "code", codes.astype(np.uint8), known
            return
        if len(known) <= 256:
            known, codes = np.unique(values, return_inverse=True)
            if len(known) <= 256:
                self.kind, self.data, self.values = "code", codes.astype(np.uint8), known
                return
        with np.errstate(invalid="ignore", over="ignore"):
            near = np.round(values * 100)
        if np.isfinite(near).all() and (np.abs(near) < 2**31).all() and (near / 100 == values).all() and not (np.signbit(values) & (values == 0)).any():
            self.kind, self.data = "hundredths", near.astype(np.int32)

    def at(self, rows: np.ndarray | slice) -> np.ndarray:
        data = self.data[rows]
        return self.values[data] if self.kind == "code" else data / 100 if self.kind == "hundredths" else data

    def some(self, rows: np.ndarray) -> _Column:
        out = object.__new__(_Column)
        out.kind, out.data, out.values = self.kind, self.data[rows], self.values
        return out

    def cut(self, threshold: float) -> float:
        """Values at most ``threshold`` are those whose ``data`` are at most this."""
        if self.kind == "code":
            return int(np.searchsorted(self.values, threshold, side="right")) - 1
        if self.kind == "plain":
            return threshold
        k = int(np.floor(min(max(threshold * 100, -(2.0**31)), 2.0**31 - 1)))
        while k < 2**31 - 1 and (k + 1) / 100 <= threshold:
            k += 1
        while k >= -(2**31) and k / 100 > threshold:
            k -= 1
        return k

    def at_most(self, threshold: float, rows) -> np.ndarray:
        cut, data = self.cut(threshold), self.data[rows]
        return np.zeros(len(data), bool) if self.kind != "plain" and cut < _LOWEST[data.dtype] else data <= cut

    def table(self, cuts: list[tuple[float, int]]) -> tuple[list | None, np.ndarray]:
        """(edges, table): bits that are left by the number of edges that a row is at most, or by code (no edges then).

        A cut takes its second number from the rows that are not at most its threshold.
        """
        if self.kind == "code":
            table = np.full(len(self.values), _ALL)
            for threshold, gone in cuts:
                table[self.cut(threshold) + 1 :] &= ~np.uint64(gone)
            return None, table
        at: dict = {}
        for threshold, gone in cuts:
            edge = self.cut(threshold)
            at[edge] = at.get(edge, 0) | gone
        edges = sorted(at)
        table = np.full(len(edges) + 1, _ALL)
        for k, edge in enumerate(edges):
            table[: len(edges) - k] &= ~np.uint64(at[edge])
        return [e for e in edges if self.kind == "plain" or e >= -(2**31)], table  # whatever the rows, none is at most a lower one


    @staticmethod
    def joined(columns: list[_Column]) -> _Column:
        """One column after another."""
        kinds, out = {c.kind for c in columns}, object.__new__(_Column)
        if kinds == {"code"}:
            known = np.unique(np.concatenate([c.values for c in columns]))
            if len(known) <= 256:
                spots = [np.searchsorted(known, c.values).astype(np.uint8) for c in columns]
                out.kind, out.values, out.data = "code", known, np.concatenate([spot[c.data] for c, spot in zip(columns, spots, strict=True)])
                return out
        if kinds == {"hundredths"}:
            out.kind, out.values, out.data = "hundredths", None, np.concatenate([c.data for c in columns])
            return out
        return _Column(np.concatenate([c.at(slice(None)) for c in columns]))


class Walk:
    """A tree made ready for many rows: subtrees of one class are leaves, and its first ``_LEAVES`` ends are met by bits.

    An inner node takes the ends on its left from the rows that go right; the first end that is left is the row's own.
    """

    def __init__(self, tree: Tree):
        self.feature, self.left, self.right, self.leaf_class = (a.tolist() for a in (tree.feature, tree.left, tree.right, tree.leaf_class))
        self.threshold = tree.threshold.tolist()
        for i in range(len(self.feature) - 1, -1, -1):  # children have higher numbers than their parents
            a, b = self.left[i], self.right[i]
            if self.feature[i] >= 0 and self.feature[a] < 0 and self.feature[b] < 0 and self.leaf_class[a] == self.leaf_class[b]:
                self.feature[i], self.leaf_class[i] = -1, self.leaf_class[a]
        self.wide = max(self.leaf_class) >= 128
        size = tree.counts.sum(axis=1).tolist() if tree.counts is not None else None
        weight, inner, ready = {0: size[0] if size else 1.0}, set(), [0]
        while len(inner) < _LEAVES - 1 and (open_ := [i for i in ready if self.feature[i] >= 0]):
            i = max(open_, key=weight.__getitem__)
            inner.add(i), ready.remove(i)
            for child in (self.left[i], self.right[i]):
                weight[child] = size[child] if size else weight[i] / 2
                ready.append(child)
        self.ends: list[int] = []
        self.cuts: dict[int, list[tuple[float, int]]] = {}
        todo: list[tuple[int, int | None]] = [(0, None)]
        while todo:  # ends from left to right; an inner node comes back once its left ones are numbered
            i, first = todo.pop()
            if first is not None:
                self.cuts.setdefault(self.feature[i], []).append((self.threshold[i], (1 << len(self.ends)) - (1 << first)))
            elif i in inner:
                todo += [(self.right[i], None), (i, len(self.ends)), (self.left[i], None)]
            else:
                self.ends.append(i)
        self.open = sum(1 << e for e, i in enumerate(self.ends) if self.feature[i] >= 0)
        self.of_class: dict[int, int] = {}
        for e, i in enumerate(self.ends):
            if self.feature[i] < 0:
                self.of_class[self.leaf_class[i]] = self.of_class.get(self.leaf_class[i], 0) | 1 << e


class _Piece:
    def __init__(self, numbers: np.ndarray, ones: np.ndarray):
        self.columns = [_Column(numbers[:, k]) for k in range(numbers.shape[1])]
        self.last = [int(o) for o in ones.max(axis=0, initial=-1)]
        self.first = [int(o) for o in ones.min(axis=0, initial=np.iinfo(ones.dtype).max)]
        self.ones = [(ones[:, k] + 1).astype(np.uint8 if last < 255 else np.uint16) for k, last in enumerate(self.last)]  # 0: no place
        self.n = len(numbers)

    def predict(self, tree: Tree | Walk) -> np.ndarray:
        """Classes of all rows: the tree's first ends by bits of all rows, the subtrees under them by parting their rows."""
        walk = tree if isinstance(tree, Walk) else Walk(tree)
        d, always = len(self.columns), _ALL
        by_place = [np.full(last + 2, _ALL) for last in self.last]  # the first one is for no place
        steps = []
        for f, cuts in walk.cuts.items():
            if f < d:
                steps.append((self.columns[f].data, *self.columns[f].table(cuts)))
                continue
            for threshold, gone in cuts:
                if not 0.0 <= threshold:
                    always &= ~np.uint64(gone)
                elif not 1.0 <= threshold:
                    for table in by_place:
                        if f - d + 1 < len(table):
                            table[f - d + 1] &= ~np.uint64(gone)
        steps += [(ones, None, table) for ones, table in zip(self.ones, by_place, strict=True) if (table != _ALL).any()]
        out = np.zeros(self.n, np.int32 if walk.wide else np.int8)
        bits, other, reached = np.empty(_STRIP, np.uint64), np.empty(_STRIP, np.uint64), np.empty(_STRIP, np.uint8)
        rows, ends = [], []
        for at in range(0, self.n, _STRIP):  # short enough for the arrays to stay in the processor's cache
            n = min(_STRIP, self.n - at)
            mine, tmp, count = bits[:n], other[:n], reached[:n]
            mine.fill(always)
            for data, edges, table in steps:
                codes = data[at : at + n]
                if edges is not None:
                    count.fill(0)
                    for edge in edges:
                        np.add(count, (codes <= edge).view(np.uint8), out=count)
                    codes = count
                np.take(table, codes, out=tmp, mode="clip")
                np.bitwise_and(mine, tmp, out=mine)
            np.bitwise_and(mine, np.negative(mine, out=tmp), out=mine)  # the first of them only
            for c, of in walk.of_class.items():
                if c:
                    met = np.bitwise_and(mine, np.uint64(of), out=tmp) != 0
                    out[at : at + n] += met * out.dtype.type(c)
            if walk.open:
                here = np.flatnonzero(np.bitwise_and(mine, np.uint64(walk.open), out=tmp))
                rows.append(here + at), ends.append(np.log2(mine[here].astype(np.float64)).astype(np.uint8))
        if walk.open:
            row, end = np.concatenate(rows), np.concatenate(ends)
            row, borders = row[np.argsort(end, kind="stable")], np.cumsum([0, *np.bincount(end, minlength=len(walk.ends))])
            for e, i in enumerate(walk.ends):
                if walk.feature[i] >= 0 and borders[e] < borders[e + 1]:
                    self._part(walk, i, row[borders[e] : borders[e + 1]], out)
        return out

    @staticmethod
    def joined(pieces: list[_Piece]) -> _Piece:
        if len(pieces) == 1:
            return pieces[0]
        out = object.__new__(_Piece)
        out.columns = [_Column.joined(list(c)) for c in zip(*(p.columns for p in pieces), strict=True)]
        out.ones = [np.concatenate(o) for o in zip(*(p.ones for p in pieces), strict=True)]
        out.last, out.first = ([f(v) for v in zip(*(getattr(p, k) for p in pieces), strict=True)] for f, k in ((max, "last"), (min, "first")))
        out.n = sum(p.n for p in pieces)
        return out

    def plain(self) -> tuple[np.ndarray, np.ndarray]:
        """(numbers, places of ones) as they came."""
        numbers, ones = np.zeros((self.n, len(self.columns))), np.full((self.n, len(self.ones)), -1, np.int16)
        for k, column in enumerate(self.columns):
            numbers[:, k] = column.at(slice(None))
        for k, places in enumerate(self.ones):
            ones[:, k] = places.astype(np.int16) - 1
        return numbers, ones

    def _part(self, walk: Walk, start: int, rows: np.ndarray, out: np.ndarray) -> None:
        """A node parts the rows that reach it, and reads no other column than its own."""
        todo = [(start, rows)]
        while todo:
            node, rows = todo.pop()
            f, threshold = walk.feature[node], walk.threshold[node]
            if f < 0:
                out[rows] = walk.leaf_class[node]
                continue
            if f < len(self.columns):
                small = self.columns[f].at_most(threshold, rows)
            else:
                place, one = f - len(self.columns), np.zeros(len(rows), bool)
                for places, first, last in zip(self.ones, self.first, self.last, strict=True):
                    if first <= place <= last:
                        one |= places[rows] == place + 1
                small = np.where(one, 1.0 <= threshold, 0.0 <= threshold)
            for child, some in ((walk.left[node], rows[small]), (walk.right[node], rows[~small])):
                if len(some):
                    todo.append((child, some))


def _in_order(pieces: list[_Piece], order: np.ndarray) -> list[_Piece]:
    """All rows in a new order, in pieces again; column by column, so that no more than one is there twice."""
    borders = range(0, len(order), PIECE)
    out = [object.__new__(_Piece) for _ in borders]
    for at, p in zip(borders, out, strict=True):
        p.n, p.columns, p.ones, p.first, p.last = min(PIECE, len(order) - at), [], [], [], []
    for k in range(len(pieces[0].columns)):
        column = _Column.joined([p.columns[k] for p in pieces])
        for p in pieces:
            p.columns[k] = None
        for at, p in zip(borders, out, strict=True):
            p.columns.append(column.some(order[at : at + PIECE]))
    for k in range(len(pieces[0].ones)):
        places = np.concatenate([p.ones[k] for p in pieces])
        first, last = min(p.first[k] for p in pieces), max(p.last[k] for p in pieces)
        for at, p in zip(borders, out, strict=True):
            p.ones.append(places[order[at : at + PIECE]]), p.first.append(first), p.last.append(last)
    return out


class Rows:
    """The rows of a block as they come, then by id: ``add`` batches, ``done`` once, ``x[rows]`` and ``predict`` after that."""

    def __init__(self):
        self._pieces: list[_Piece] = []
        self._open: list[tuple] = []
        self._packed: list[_Piece] = []  # these come alone or not at all
        self._ids, self._labels, self._waiting, self.width = [], [], 0, 0

    def add(self, ids: np.ndarray, numbers: np.ndarray, ones: np.ndarray, width: int, labels: np.ndarray) -> None:
        self._ids.append(ids.astype(np.int64)), self._labels.append(labels.astype(np.int16)), self._open.append((numbers, ones))
        self._waiting, self.width = self._waiting + len(ids), width
        if self._waiting >= PIECE:
            self._close()

    def add_packed(self, packed: bytes) -> None:
        """Rows that ``pack_rows`` has put together."""
        ids, labels, piece, width = pickle.loads(packed)
        self._ids.append(ids), self._labels.append(labels), self._packed.append(piece)
        self._waiting, self.width = self._waiting + piece.n, width
        if self._waiting >= PIECE:
            self._close()

    def _close(self) -> None:
        made = [_Piece(np.concatenate([p[0] for p in self._open]), np.concatenate([p[1] for p in self._open]))] if self._open else []
        self._pieces.append(_Piece.joined(self._packed + made))
        self._open, self._packed, self._waiting = [], [], 0

    def done(self) -> tuple[np.ndarray | Rows, np.ndarray]:
        """(features, labels) in the order of ids; blocks of less than a piece are one dense matrix."""
        order = np.argsort(np.concatenate(self._ids), kind="stable").astype(np.int32)
        self._ids = []
        y = np.concatenate(self._labels)[order].astype(np.int64 if not self._pieces else np.int16)
        self._labels = []
        if not self._pieces:
            self._open += [p.plain() for p in self._packed]
            return dense(np.concatenate([p[0] for p in self._open]), np.concatenate([p[1] for p in self._open]), self.width)[order], y
        if self._waiting:
            self._close()
        self._pieces = _in_order(self._pieces, order)
        self._first = np.cumsum([0, *(p.n for p in self._pieces)])
        self.shape = (len(order), len(self._pieces[0].columns) + self.width)
        return self, y

    def __len__(self) -> int:
        return self.shape[0]

    def __getitem__(self, rows: np.ndarray) -> np.ndarray:
        """Some rows as a dense matrix."""
        where = rows
        piece = np.searchsorted(self._first, where, side="right") - 1
        d = len(self._pieces[0].columns)
        numbers, ones = np.zeros((len(where), d)), np.full((len(where), len(self._pieces[0].ones)), -1, np.int16)
        for p in np.unique(piece):
            here = np.flatnonzero(piece == p)
            local = where[here] - self._first[p]
            for k, column in enumerate(self._pieces[p].columns):
                numbers[here, k] = column.at(local)
            for k, places in enumerate(self._pieces[p].ones):
                ones[here, k] = places[local].astype(np.int16) - 1
        return dense(numbers, ones, self.width)

    def predict(self, tree: Tree) -> np.ndarray:
        walk = Walk(tree)
        return np.concatenate([p.predict(walk) for p in self._pieces])
