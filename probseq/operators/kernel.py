"""The numerical core: many sequences at once, one pattern node after another.

Events of a batch are numbered through, with a spare number after each sequence. A node of the pattern tree is the sorted
list of events where its pattern can end, with the best probability there. A child comes from its parent by one merge
with the occurrences of its item: an s-extension takes the parent's best before an event, an i-extension the parent's
value at it. So a node costs its matches, whatever its depth, and all descendants share the work of their prefix. Where only
supports are wanted, all children of a node come from one look at what follows its first ends (`totals`).

Extensions of a node read a matrix (event x item) of suffix maxima: its row after a node's first end in a sequence holds
the best probability of every item from there on, so statistics of all s-extensions are column sums of gathered rows. Where
the alphabet is too wide for the matrix, the occurrences of the node's sequences are listed instead.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa

CELLS = 1 << 22  # events x items of a batch's matrix, where sequences can be split so
WIDEST = 1 << 25  # cells beyond which a batch lists occurrences instead
GATHER = 1 << 20  # cells that a node gathers at once


def spans(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    total = int(lengths.sum())
    return np.repeat(starts - (np.cumsum(lengths) - lengths), lengths) + np.arange(total)


def suffix_best(group: np.ndarray, p: np.ndarray) -> np.ndarray:
    """Per row the largest p from it to the end of its group; rows of a group are adjacent and in order."""
    best, step, n = p.copy(), 1, len(p)
    last = np.bincount(group).max() if n else 0
    while step < last:
        same = group[:-step] == group[step:]
        best[:-step] = np.where(same, np.maximum(best[:-step], best[step:]), best[:-step])
        step *= 2
    return best


def prefix_best(starts: np.ndarray, p: np.ndarray) -> np.ndarray:
    """Per row the largest p from the start of its group to it; `starts` are the first rows of the groups."""
    best, step, n = p.copy(), 1, len(p)
    place = np.arange(n) - np.repeat(starts, np.diff(np.append(starts, n)))
    last = int(place.max()) + 1 if n else 0
    while step < last:
        ahead = np.where(place[step:] >= step, np.maximum(best[step:], best[:-step]), best[step:])
        best[step:] = ahead
        step *= 2
    return best


class State:
    """Where a pattern can end: events in order, and the best probability at each."""

    def __init__(self, ev: np.ndarray, val: np.ndarray, owner: np.ndarray):
        self.ev, self.val = ev, val
        seq = owner[ev]
        new = np.ones(len(ev), bool)
        new[1:] = seq[1:] != seq[:-1]
        self.starts = np.flatnonzero(new)
        self.rows = seq[self.starts]  # sequences that have the pattern

    @cached_property
    def best(self) -> np.ndarray:
        """The best probability in each sequence."""
        return np.maximum.reduceat(self.val, self.starts)

    @cached_property
    def so_far(self) -> np.ndarray:
        """The best probability up to each end, within its sequence."""
        return prefix_best(self.starts, self.val)


class Batch:
    """Packed sequences: lengths, and event key, item id and probability of all occurrences, by (event, item) in each."""

    def __init__(self, lengths: np.ndarray, pos: np.ndarray, item: np.ndarray, p: np.ndarray, n_items: int = 0):
        self.n, self.n_items = len(lengths), n_items
        row = np.repeat(np.arange(self.n), lengths)
        new = np.ones(len(pos), bool)
        new[1:] = (pos[1:] != pos[:-1]) | (row[1:] != row[:-1])
        self.ev = np.cumsum(new) - 1 + row
        self.row, self.item, self.p = row, item, p
        many = np.bincount(row[new], minlength=self.n) + 1
        self.owner = np.repeat(np.arange(self.n), many)
        self.begin = np.cumsum(many) - many
        self.longest = int(many.max()) if self.n else 0
        self.together = not new.all()
        by = np.argsort(item, kind="stable")
        self.items, begin = np.unique(item[by], return_index=True)
        stop = np.append(begin[1:], len(by))
        self.places = {int(i): (self.ev[by[a:b]], p[by[a:b]]) for i, a, b in zip(self.items, begin, stop, strict=True)}
        self.lengths = lengths

    def child(self, parent: State | None, kind: str, item: int) -> State | None:
        """The node below `parent` (None: the root); None where it does not occur."""
        at = self.places.get(item)
        if at is None:
            return None
        ev, p = at
        if parent is None:
            return State(ev, p, self.owner)
        place = np.searchsorted(parent.ev, ev)
        if kind == "S":
            place -= 1
            hit = place >= 0
            hit &= self.owner[parent.ev[place]] == self.owner[ev]
            value = parent.so_far[place[hit]] * p[hit]
        else:
            place[place == len(parent.ev)] = 0
            hit = parent.ev[place] == ev
            value = parent.val[place[hit]] * p[hit]
        ev, some = ev[hit], value > 0
        return State(ev[some], value[some], self.owner) if some.any() else None

    @cached_property
    def stops(self) -> np.ndarray:
        """Where the occurrences of each sequence end."""
        return np.cumsum(self.lengths)

    @cached_property
    def counts(self) -> np.ndarray:
        return np.bincount(self.item) if len(self.item) else np.zeros(0, np.int64)

    @cached_property
    def columns(self) -> np.ndarray:
        """-1 for every item; `grown` writes its own numbers into it and takes them back."""
        return np.full(len(self.counts), -1, np.int64)

    def grown(self, parent: State, kind: str, items: np.ndarray, most: int | None = None) -> tuple[np.ndarray, ...] | None:
        """(which of `items`, which of the parent's sequences, event, probability), by event, of all that extends the
        parent by one of the distinct `items`; None where more than `most` occurrences would have to be looked at."""
        of = np.arange(len(parent.rows))
        if kind == "S":
            begin = np.searchsorted(self.ev, parent.ev[parent.starts], side="right")
            many = self.stops[parent.rows] - begin
        else:
            begin = np.searchsorted(self.ev, parent.ev)
            many = np.searchsorted(self.ev, parent.ev, side="right") - begin
            of = np.repeat(of, np.diff(np.append(parent.starts, len(parent.ev))))
        if most is not None and many.sum() > most:
            return None
        known = np.flatnonzero((items >= 0) & (items < len(self.columns)))
        self.columns[items[known]] = known
        at = spans(begin, many)
        col = self.columns[self.item[at]]
        self.columns[items[known]] = -1
        hit = np.flatnonzero(col >= 0)
        col, at = col[hit], at[hit]
        ev = self.ev[at]
        if kind == "S":
            value = parent.so_far[np.searchsorted(parent.ev, ev) - 1] * self.p[at]
        else:
            value = np.repeat(parent.val, many)[hit] * self.p[at]
        row = np.repeat(of, many)[hit]
        if not (value > 0).all():
            some = value > 0
            col, row, ev, value = col[some], row[some], ev[some], value[some]
        return col, row, ev, value

    @cached_property
    def tops(self) -> np.ndarray:
        """For every sequence and item the largest p."""
        m = np.zeros((self.n, len(self.counts)))
        np.maximum.at(m, (self.row, self.item), self.p)
        return m

    @cached_property
    def matrix(self) -> np.ndarray:
        """Suffix maxima: for every event (and spare) and item the largest p from there to the end of the sequence."""
        m = np.zeros((len(self.owner), self.n_items))
        m[self.ev, self.item] = self.p
        step = 1
        while step < self.longest:
            np.maximum(m[:-step], m[step:], out=m[:-step], where=(self.owner[:-step] == self.owner[step:])[:, None])
            step *= 2
        return m

    @cached_property
    def beside(self) -> np.ndarray:
        """The matrix where the item stands in the event itself."""
        m = np.zeros_like(self.matrix)
        m[self.ev, self.item] = self.matrix[self.ev, self.item]
        return m

    @cached_property
    def at_event(self) -> np.ndarray:
        m = np.zeros((len(self.owner), self.n_items))
        m[self.ev, self.item] = self.p
        return m

    @cached_property
    def listed(self) -> tuple[np.ndarray, ...]:
        """Occurrences by (sequence, item, event), with suffix maxima: for extensions without a matrix."""
        own = np.lexsort((self.ev, self.item, self.row))
        row, item = self.row[own], self.item[own]
        fresh = np.ones(len(own), bool)
        fresh[1:] = (row[1:] != row[:-1]) | (item[1:] != item[:-1])
        return self.ev[own], item, self.p[own], suffix_best(np.cumsum(fresh) - 1, self.p[own]), np.cumsum(self.lengths) - self.lengths

    def extensions(self, node: State | None, last: int, cooccurring: bool) -> list[tuple[str, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """Per kind: items, and maximum, sum and count over sequences of the best probability that extends the node."""
        if len(self.owner) * self.n_items > WIDEST:
            return self._by_list(node, last, cooccurring)
        first = self.begin if node is None else node.ev[node.starts] + 1
        out = [("S", 0, self._columns(first, None, self.matrix, 0))]
        if node is not None and self.together:
            out.append(("I", last + 1, self._columns(node.ev, node.starts, self.at_event if cooccurring else self.beside, last + 1)))
        found = []
        for kind, low, (mx, sm, ct) in out:
            hit = np.flatnonzero(ct)
            if len(hit):
                found.append((kind, hit + low, mx[hit], sm[hit], ct[hit]))
        return found

    def _columns(self, rows: np.ndarray, starts: np.ndarray | None, m: np.ndarray, low: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Maximum, sum and count by column of m[rows, low:], with `starts` of the maxima of its groups of rows."""
        width = m.shape[1] - low
        mx, sm, ct = np.zeros(width), np.zeros(width), np.zeros(width, np.int64)
        if not width:
            return mx, sm, ct
        step = max(1, GATHER // width)
        if starts is None:
            cuts = np.arange(0, len(rows), step)
        else:  # groups stay whole
            cuts = starts[np.unique(np.searchsorted(starts, np.arange(0, len(rows), step)).clip(0, len(starts) - 1))]
            cuts[:1] = 0
        for a, b in zip(cuts.tolist(), [*cuts[1:].tolist(), len(rows)], strict=True):
            x = m[rows[a:b], low:]
            if starts is not None:
                own = starts[(starts >= a) & (starts < b)] - a
                x = np.maximum.reduceat(x, own, axis=0)
            mx = np.maximum(mx, x.max(axis=0))
            sm += x.sum(axis=0)
            ct += np.count_nonzero(x, axis=0)
        return mx, sm, ct

    def _by_list(self, node: State | None, last: int, cooccurring: bool):
        ev, item, p, best, first = self.listed
        rows = np.arange(self.n) if node is None else node.rows
        at = spans(first[rows], self.lengths[rows])
        own = np.repeat(np.arange(len(rows)), self.lengths[rows])
        out = []
        if node is None:
            later = np.ones(len(at), bool)
        else:
            later = ev[at] > node.ev[node.starts][own]
        for kind in ("S", "I"):
            if kind == "S":
                keep = later
            elif node is None or not self.together:
                continue
            else:
                place = np.searchsorted(node.ev, ev[at])
                place[place == len(node.ev)] = 0
                keep = (item[at] > last) & (node.ev[place] == ev[at])
            a, r, i = at[keep], own[keep], item[at[keep]]
            if not len(a):
                continue
            new = np.ones(len(a), bool)
            new[1:] = (r[1:] != r[:-1]) | (i[1:] != i[:-1])
            if kind == "I" and cooccurring:
                value = np.maximum.reduceat(p[a], np.flatnonzero(new))
            else:  # suffix maxima fall along a sequence: the first is the largest
                value = best[a[new]]
            i = i[new]
            by = np.argsort(i, kind="stable")
            i, value = i[by], value[by]
            cut = np.flatnonzero(np.concatenate([[True], i[1:] != i[:-1]]))
            out.append((kind, i[cut], np.maximum.reduceat(value, cut), np.add.reduceat(value, cut), np.diff(np.append(cut, len(i)))))
        return out


def best_sums(col: np.ndarray, row: np.ndarray, value: np.ndarray, n_cols: int, n_rows: int, beside: np.ndarray | None = None) -> tuple[np.ndarray, ...]:
    """By column the sum over rows of the largest value, and the number of rows; with `beside` (row x item) also the sum of
    the largest value times a row's own."""
    key = col * n_rows + row
    if n_cols * n_rows <= 4 * len(value) + 1024:
        m = np.zeros(n_cols * n_rows)
        np.maximum.at(m, key, value)
        m = m.reshape(n_cols, n_rows)
        return m.sum(axis=1), np.count_nonzero(m, axis=1), None if beside is None else m @ beside
    es, support = np.zeros(n_cols), np.zeros(n_cols, np.int64)
    cross = None if beside is None else np.zeros((n_cols, beside.shape[1]))
    if len(value):
        by = np.argsort(key, kind="stable")
        key = key[by]
        cut = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        best, col, row = np.maximum.reduceat(value[by], cut), key[cut] // n_rows, key[cut] % n_rows
        first = np.flatnonzero(np.concatenate([[True], col[1:] != col[:-1]]))
        es[col[first]] = np.add.reduceat(best, first)
        support[col[first]] = np.diff(np.append(first, len(col)))
        if cross is not None:
            cross[col[first]] = np.add.reduceat(best[:, None] * beside[row], first, axis=0)
    return es, support, cross


def gathered(columns, least: int = CELLS // 8):
    """Consecutive list arrays put together until they hold `least` values, so that a tree is not walked for a few rows."""
    held, size = [], 0
    for c in columns:
        held.append(c)
        size += c.offsets[-1].as_py() - c.offsets[0].as_py()
        if size >= least:
            yield held[0] if len(held) == 1 else pa.concat_arrays(held)
            held, size = [], 0
    if held:
        yield held[0] if len(held) == 1 else pa.concat_arrays(held)


def batches_of(column: pa.ListArray, n_items: int = 0, cells: int = CELLS):
    """(first row, Batch) of consecutive sequences; occurrences x items stay within `cells` where they can."""
    off = column.offsets.to_numpy().astype(np.int64)
    flat = column.values
    pos, item, p = (flat.field(k).to_numpy(zero_copy_only=False) for k in ("pos", "item", "p"))
    lengths = np.diff(off)
    most = max(1, cells // max(n_items, 8))
    at, n = 0, len(lengths)
    while at < n:
        to = max(at + 1, int(np.searchsorted(off + np.arange(n + 1), off[at] + at + most, side="right")) - 1)
        to = min(to, n)
        a, b = off[at], off[to]
        yield at, Batch(lengths[at:to], pos[a:b], item[a:b], p[a:b], n_items)
        at = to


@dataclass
class Tree:
    """Nodes parents-first: parent (-1 for children of the root), kind and item."""

    parent: np.ndarray
    kind: np.ndarray  # bytes S and I
    item: np.ndarray

    def children(self) -> dict[int, list[int]]:
        out: dict[int, list[int]] = {}
        for k, p in enumerate(self.parent.tolist()):
            out.setdefault(p, []).append(k)
        return out


def walk(batch: Batch, tree: Tree, children: dict[int, list[int]], visit) -> None:
    """Depth-first over the tree; visit(node, state) for every node that occurs. A node that does not occur ends its branch."""
    stack: list = [(k, None) for k in reversed(children.get(-1, []))]
    while stack:
        k, parent = stack.pop()
        state = batch.child(parent, "S" if tree.kind[k] == b"S" else "I", int(tree.item[k]))
        if state is None:
            continue
        visit(k, state)
        stack += [(c, state) for c in reversed(children.get(k, []))]


class Families:
    """The children of every node of a tree by kind, as slices of one order of the nodes."""

    def __init__(self, tree: Tree):
        together = (tree.kind != b"S").astype(np.int64)
        key = tree.parent * 2 + together
        self.order = np.lexsort((tree.item, key))
        edges = np.arange(-2, 2 * len(tree.parent) + 1)
        self.edges = np.searchsorted(key[self.order], edges)
        self.leaf = np.ones(len(tree.parent), bool)
        self.leaf[tree.parent[tree.parent >= 0]] = False

    def of(self, node: int, kind: str) -> np.ndarray:
        k = 2 * node + 2 + (kind != "S")
        return self.order[self.edges[k] : self.edges[k + 1]]


def totals(batch: Batch, tree: Tree, families: Families, es: np.ndarray, support: np.ndarray, cross: np.ndarray | None = None) -> None:
    """Adds the expected support and the number of sequences of every node of the tree, and to `cross` (node x item) for
    every leaf the sum over sequences of its best probability times the item's.

    Children of a node are found together, or one by one where their items' occurrences are fewer than what follows the
    node's first ends.
    """
    stack = [(k, batch.child(None, "S", int(tree.item[k]))) for k in families.of(-1, "S").tolist()]
    while stack:
        k, state = stack.pop()
        if state is None:
            continue
        es[k] += state.best.sum()
        support[k] += len(state.rows)
        if cross is not None and families.leaf[k]:
            cross[k, : batch.tops.shape[1]] += state.best @ batch.tops[state.rows]
        for kind in ("S", "I"):
            own = families.of(k, kind)
            if not len(own) or (kind == "I" and not batch.together):
                continue
            items = tree.item[own]
            alone = int(batch.counts[items[(items >= 0) & (items < len(batch.counts))]].sum()) + 2000 * len(own)
            found = batch.grown(state, kind, items, alone)
            if found is None:
                stack += [(c, batch.child(state, kind, i)) for c, i in zip(own.tolist(), items.tolist(), strict=True)]
                continue
            col, row, ev, value = found
            leaf = families.leaf[own]
            if leaf.any():
                mine = slice(None) if leaf.all() else leaf[col]
                e, n, c = best_sums(col[mine], row[mine], value[mine], len(own), len(state.rows), None if cross is None else batch.tops[state.rows])
                es[own] += e
                support[own] += n
                if cross is not None:
                    cross[own, : c.shape[1]] += c
            if not leaf.all():
                by = np.argsort(col, kind="stable")
                edges = np.searchsorted(col[by], np.arange(len(own) + 1))
                for c in np.flatnonzero(~leaf & (np.diff(edges) > 0)).tolist():
                    at = by[edges[c] : edges[c + 1]]
                    stack.append((int(own[c]), State(ev[at], value[at], batch.owner)))


def pairwise_best(events: list[dict[int, float]], steps: list[list[int]]) -> tuple[float, int]:
    """(best match probability, pair operations) by comparing every pair of events for each event of the pattern."""
    ops, ends = 0, None
    for wanted in steps:
        new = []
        for m, event in enumerate(events):
            p = 1.0
            for i in wanted:
                p *= event.get(i, 0.0)
            best = 1.0 if ends is None else 0.0
            if ends is not None:
                for e in ends[:m]:
                    ops += 1
                    best = max(best, e)
            new.append(p * best)
        ends = new
    return max(ends, default=0.0), ops
