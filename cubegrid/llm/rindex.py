"""A run-length index over a set of short strings: run-compressed Burrows-Wheeler transform, suffix
samples at run ends, backward steps in lockstep over many patterns, and location by predecessor
steps from the samples.

Strings are kept apart by end marks that sort by string number, so no match crosses strings.
"""

from __future__ import annotations

import numpy as np

from cubegrid.llm.common import starts_of


#: Symbols that are packed into one number to begin the suffix order with.
_PACKED = 7


def _refined(rank: np.ndarray, who: np.ndarray, second: np.ndarray) -> np.ndarray:
    """Order the members of whole groups of equal ``rank`` by ``second``, in place; those still tied.

    A group's rank is the number of suffixes before it, so a group keeps its place whatever others do.
    """
    if not len(who):
        return who
    key = rank[who] * (len(rank) + 1) + second
    order = np.argsort(key)
    key, who = key[order], who[order]
    old = rank[who]
    each = np.arange(len(who))
    opens = np.concatenate([[True], old[1:] != old[:-1]])
    slot = old + each - np.maximum.accumulate(np.where(opens, each, 0))
    new = np.concatenate([[True], key[1:] != key[:-1]])
    rank[who] = np.maximum.accumulate(np.where(new, slot, 0))
    return who[~(new & np.append(new[1:], True))]


def _suffix_ranks(symbols: np.ndarray, left: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(rank, class) of every suffix: its place in order, and a number equal where the first ``width`` symbols are.

    ``symbols`` are 1 to 256 and 0 for an end mark, ``left`` the symbols before the next mark. Marks sort
    before all else and by place, so suffixes that end within what is compared are told apart at once.
    """
    n = len(symbols)
    depths = [width]
    while depths[-1] > _PACKED:
        depths.append(-(-depths[-1] // 2))
    depth = depths.pop()
    packed = np.zeros(n, np.int64)
    for i in range(depth):  # nothing counts beyond the mark
        packed[: n - i] |= np.where(left[: n - i] >= i, symbols[i:], 0) << (9 * (depth - 1 - i))
    order = np.argsort(packed)
    packed = packed[order]
    new = np.concatenate([[True], packed[1:] != packed[:-1]])
    rank = np.empty(n, np.int64)
    rank[order] = np.maximum.accumulate(np.where(new, np.arange(n), 0))
    tied = order[~(new & np.append(new[1:], True))]
    ended = left[tied] < depth  # whole groups: what ends in equal symbols ends at the same distance
    _refined(rank, tied[ended], tied[ended])
    tied = tied[~ended]
    at_width = None if depths else rank.copy()
    while len(tied):
        step = min(depth, depths[-1] - depth) if depths else depth
        goal = depths.pop() if depths else 2 * depth
        # ties reach ``depth`` symbols without a mark, so what stands ahead is in range; all of it is read before any changes
        tied = _refined(rank, tied, rank[tied + step])
        depth = goal
        if at_width is None and depth == width:
            at_width = rank.copy()
    return rank, rank if at_width is None else at_width


class RunLengthIndex:
    """Index of strings of at most ``longest`` bytes for matches of ``width`` bytes."""

    def __init__(self, data: np.ndarray, lengths: np.ndarray, width: int):
        self.width = width
        n_strings = len(lengths)
        self.begin = starts_of(lengths + 1)[:-1]
        n = int(lengths.sum()) + n_strings
        mark = self.begin + lengths
        plain = np.ones(n, bool)
        plain[mark] = False
        symbols = np.zeros(n, np.int64)
        symbols[plain] = data.astype(np.int64) + 1
        small = np.int32 if n < 1 << 31 else np.int64
        rank, at_width = _suffix_ranks(symbols, np.repeat(mark, lengths + 1) - np.arange(n), width)
        suffix = np.empty(n, np.int64)
        suffix[rank] = np.arange(n)
        self.n = n
        # the transform, its runs, and the number of smaller characters
        code = symbols - 1 + n_strings
        last = np.concatenate([[0], code[:-1]])[suffix]
        opening = np.zeros(n, np.int64)
        opening[self.begin] = -1 - np.arange(n_strings)  # before a first character: a mark of its own
        last = np.where(opening[suffix] < 0, opening[suffix], last)
        cut = np.flatnonzero(np.concatenate([[True], last[1:] != last[:-1]]))
        self.run_start, self.run_char = cut, last[cut]
        run_len = np.diff(np.append(cut, n))
        self.run_of = np.repeat(np.arange(len(cut), dtype=small), run_len)
        self.run_byte = np.where(self.run_char >= 0, self.run_char - n_strings, -1)
        self.smaller = np.concatenate([[n_strings], n_strings + np.cumsum(np.bincount(data, minlength=256))])
        # ranks: runs grouped by character
        order = np.lexsort((self.run_start, self.run_char))
        kept = order[self.run_char[order] >= 0]
        self.key_char = self.run_char[kept] - n_strings
        self.key = self.key_char * (n + 1) + self.run_start[kept]
        self.key_len = run_len[kept]
        total = np.cumsum(self.key_len) - self.key_len
        first = np.searchsorted(self.key_char, self.key_char)
        self.key_sum = total - total[first]
        self.run_sum = np.zeros(len(cut), np.int64)  # how often a run's character stands before it
        self.run_sum[kept] = self.key_sum
        # samples: text position at the head of each run, and what stands one row above it
        heads = suffix[cut]
        above = np.where(cut > 0, suffix[np.maximum(cut - 1, 0)], -1)
        by_text = np.argsort(heads, kind="stable")
        self.head_text, self.head_above = heads[by_text], above[by_text]
        self.step_above = self.head_above - self.head_text
        # the sample at or before a text position, and the string it lies in
        self.sample_of = np.repeat(np.arange(-1, len(heads), dtype=small), np.diff(np.concatenate([[0], self.head_text, [n]])))
        self.string_of = np.repeat(np.arange(n_strings, dtype=small), lengths + 1)
        # intervals of equal first ``width`` characters, and the sample at their last rows
        same = at_width[suffix]
        opens = np.flatnonzero(np.concatenate([[True], same[1:] != same[:-1]]))
        self.open_row, self.close_row = opens, np.append(opens[1:], n)
        self.close_text = suffix[self.close_row - 1]
        self.interval_of = np.repeat(np.arange(len(opens), dtype=small), self.close_row - self.open_row)

    @property
    def runs(self) -> int:
        return len(self.run_start)

    def rank(self, char: np.ndarray, row: np.ndarray) -> np.ndarray:
        """How often each character stands in the transform before a row.

        Within a run of the character, or right behind it, the run says so; else the last such run is searched for.
        """
        run = self.run_of[np.maximum(row - 1, 0)]
        out = self.run_sum[run] + row - self.run_start[run]
        away = np.flatnonzero((self.run_byte[run] != char) | (row == 0))
        out[away] = self._rank_before(char[away], row[away])
        return out

    def _rank_before(self, char: np.ndarray, row: np.ndarray) -> np.ndarray:
        i = np.searchsorted(self.key, char * (self.n + 1) + row, "left") - 1
        ok = i >= 0
        j = np.maximum(i, 0)
        ok &= self.key_char[j] == char
        start = self.key[j] - char * (self.n + 1)
        return np.where(ok, self.key_sum[j] + np.minimum(row - start, self.key_len[j]), 0)

    def stream(self, data: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Matching statistics of patterns, cut off at ``width``: per pattern byte the matched length
        (of what starts there) and the interval of equal ``width`` characters, or -1.

        All patterns take their steps from right to left together. A match that grows past the
        width is cut to it by widening the rows to their interval.
        """
        begin = starts_of(lengths)[:-1]
        matched = np.zeros(len(data), np.int64)
        interval = np.full(len(data), -1, np.int64)
        lo, hi = np.zeros(len(lengths), np.int64), np.full(len(lengths), self.n, np.int64)
        size = np.zeros(len(lengths), np.int64)
        for back in range(1, int(lengths.max(initial=0)) + 1):
            live = np.flatnonzero(lengths >= back)
            at = begin[live] + lengths[live] - back
            c = data[at].astype(np.int64)
            a = self.smaller[c] + self.rank(c, lo[live])
            b = self.smaller[c] + self.rank(c, hi[live])
            lost = a >= b  # no such match: begin anew with this character alone
            a[lost], b[lost] = self.smaller[c[lost]], self.smaller[c[lost] + 1]
            grown = np.where(lost, (a < b).astype(np.int64), size[live] + 1)
            full = grown >= self.width
            k = self.interval_of[a[full]]
            a[full], b[full] = self.open_row[k], self.close_row[k]
            grown[full] = self.width
            lo[live], hi[live], size[live] = a, b, grown
            matched[at] = grown
            interval[at[full]] = k
        return matched, interval

    def above(self, text: np.ndarray) -> np.ndarray:
        """The text position one row above that of ``text``, from the sample before it."""
        return self.step_above[self.sample_of[text]] + text

    def least(self, intervals: np.ndarray, owner_value: np.ndarray) -> np.ndarray:
        """The least value of the strings in which each (distinct) interval occurs."""
        text = self.close_text[intervals]
        left = self.close_row[intervals] - self.open_row[intervals] - 1
        best = owner_value[self.string_of[text]]
        live = np.flatnonzero(left > 0)
        text = text[live]
        while len(live):
            text = self.above(text)
            best[live] = np.minimum(best[live], owner_value[self.string_of[text]])
            left[live] -= 1
            more = left[live] > 0
            live, text = live[more], text[more]
        return best
