"""A deterministic transducer over characters for a vocabulary of ranked merges.

Where two tokens may stand side by side, undoing the later of their merges
again and again never finds a merge that should have come before: such pairs
are compatible. A text's tokens end, at every character, in the one vocabulary
suffix that is compatible with the token before it. So the state is the suffix
automaton's place in the vocabulary and the tokens that ended within its reach;
a character leads to one next state and its transition is annotated with the
tokens that it adds. Many strings are read side by side.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np

#: Strings of more characters are read alone.
SIDE_BY_SIDE = 64

#: Pairs whose compatibility is remembered; beyond it they are worked out anew.
MAX_PAIRS = 4_000_000


def _merged(text: str, rank: dict[str, int], below: int) -> list[str]:
    """Tokens of ``text`` by merges of ranks below ``below``, best first, leftmost first."""
    parts = list(text)
    while len(parts) > 1:
        best, at = min((rank.get(a + b, below), k) for k, (a, b) in enumerate(zip(parts, parts[1:])))
        if best >= below:
            break
        parts[at : at + 2] = [parts[at] + parts[at + 1]]
    return parts


class Transducer:
    """Compiled from single characters and merged pieces, the latter in the order in which they merge."""

    def __init__(self, characters: Sequence[str], pieces: Sequence[str]) -> None:
        singles = sorted(characters)
        rank = {p: k for k, p in enumerate(pieces)}
        number = {c: k for k, c in enumerate(singles)}
        left, right = list(range(len(singles))), list(range(len(singles)))
        names = list(singles)
        for k, p in enumerate(pieces):
            halves = _merged(p, rank, k)
            # a piece that its own characters never merge to is never emitted
            if len(halves) == 2 and all(h in number for h in halves):
                number[p] = len(names)
                names.append(p)
                left.append(number[halves[0]])
                right.append(number[halves[1]])
            elif len(_merged(p, rank, len(pieces))) == 1:
                raise ValueError("a piece is merged from pieces that come after it")
        self.singles, self.size = len(singles), len(names)
        self.left, self.right = np.array(left, np.int64), np.array(right, np.int64)
        keys = self.left[self.singles :] * self.size + self.right[self.singles :]
        order = np.argsort(keys)
        self.pair, self.of_pair = keys[order], order + self.singles
        self.length = np.array([len(x) for x in names], np.int64)
        self._automaton(names)
        self._seen = np.empty(0, np.int64)
        self._fits = np.empty(0, bool)

    def _automaton(self, names: list[str]) -> None:
        """Transitions of the suffix automaton of all names; per state the longest name that ends there, per name the next shorter one."""
        char = {c: k + 1 for k, c in enumerate(names[: self.singles])}
        self.char = np.zeros(max(map(ord, char), default=0) + 2, np.int32)
        for c, k in char.items():
            self.char[ord(c)] = k
        width = self.singles + 1
        step: dict[int, int] = {}
        end, depth_first = [-1], [[0]]
        for token, name in enumerate(names):
            state = 0
            for d, c in enumerate(name):
                key = state * width + char[c]
                if key not in step:
                    step[key] = len(end)
                    end.append(-1)
                    if len(depth_first) <= d + 1:
                        depth_first.append([])
                    depth_first[d + 1].append(key)
                state = step[key]
            end[state] = token
        fail, out, shorter = [0] * len(end), list(end), [-1] * len(names)
        for level in depth_first[1:]:
            for key in level:
                state, (parent, c) = step[key], divmod(key, width)
                if parent:
                    back = fail[parent]
                    while back and back * width + c not in step:
                        back = fail[back]
                    fail[state] = step.get(back * width + c, 0)
                if end[state] >= 0:
                    shorter[end[state]] = out[fail[state]]
                else:
                    out[state] = out[fail[state]]
        self.width = width
        keys = np.array(sorted(step), np.int64)
        self.key, self.to = keys, np.array([step[k] for k in keys.tolist()], np.int64)
        self.fail, self.out, self.shorter = (np.array(x, np.int64) for x in (fail, out, shorter))

    def _next(self, state: np.ndarray, char: np.ndarray) -> np.ndarray:
        state, left = state.copy(), np.arange(len(state))
        out = np.zeros(len(state), np.int64)
        while len(left):
            asked = state[left] * self.width + char[left]
            at = np.minimum(np.searchsorted(self.key, asked), len(self.key) - 1)
            hit = self.key[at] == asked
            out[left[hit]] = self.to[at[hit]]
            left = left[~hit]
            left = left[state[left] > 0]
            state[left] = self.fail[state[left]]
        return out

    def _compatible(self, one: np.ndarray, two: np.ndarray) -> np.ndarray:
        """Whether the tokens may stand side by side."""
        ok, left = np.zeros(len(one), bool), np.arange(len(one))
        one, two, limit = one.copy(), two.copy(), np.full(len(one), self.size + 1)
        while len(left):
            a, b = one[left], two[left]
            asked = a * self.size + b
            at = np.minimum(np.searchsorted(self.pair, asked), max(len(self.pair) - 1, 0))
            sooner = (self.pair[at] == asked) & (self.of_pair[at] < limit[left]) if len(self.pair) else np.zeros(len(left), bool)
            left, a, b = left[~sooner], a[~sooner], b[~sooner]
            # the later merge is undone; a character cannot be
            undo_one = np.where(a >= self.singles, (b < self.singles) | (a > b), False)
            undo_two = ~undo_one & (b >= self.singles)
            ok[left[~undo_one & ~undo_two]] = True
            one[left[undo_one]], limit[left[undo_one]] = self.right[a[undo_one]], a[undo_one]
            # of equal merges the left one comes first
            two[left[undo_two]], limit[left[undo_two]] = self.left[b[undo_two]], b[undo_two] + 1
            left = left[undo_one | undo_two]
        return ok

    def fits(self, one: np.ndarray, two: np.ndarray) -> np.ndarray:
        asked = one * self.size + two
        at = np.minimum(np.searchsorted(self._seen, asked), max(len(self._seen) - 1, 0))
        known = self._seen[at] == asked if len(self._seen) else np.zeros(len(asked), bool)
        if not known.all():
            new = np.unique(asked[~known])
            if len(self._seen) + len(new) > MAX_PAIRS:
                self._seen, self._fits, new = np.empty(0, np.int64), np.empty(0, bool), np.unique(asked)
            found = self._compatible(*np.divmod(new, self.size))
            seen = np.concatenate([self._seen, new])
            order = np.argsort(seen, kind="stable")
            self._seen, self._fits = seen[order], np.concatenate([self._fits, found])[order]
            at = np.searchsorted(self._seen, asked)
        return self._fits[at]

    def counts(self, texts: Sequence[str]) -> tuple[np.ndarray, np.ndarray]:
        """(tokens of each string, whether its first token is its first character alone)."""
        size = np.array([len(t) for t in texts], np.int64)
        count, alone = np.zeros(len(texts), np.int64), np.zeros(len(texts), bool)
        for k in np.flatnonzero(size > SIDE_BY_SIDE).tolist():
            count[k], alone[k] = self._one(texts[k])
        some = np.flatnonzero((size <= SIDE_BY_SIDE) & (size > 0))
        some = some[np.argsort(-size[some], kind="stable")]
        if len(some):
            size = size[some]
            points = np.frombuffer("".join([texts[k] for k in some.tolist()]).encode("utf-32-le", "surrogatepass"), np.uint32)
            count[some], alone[some] = self._many(points, size)
        return count, alone

    def _ids(self, points: np.ndarray) -> np.ndarray:
        return np.where(points < len(self.char), self.char[np.minimum(points, len(self.char) - 1)], 0)

    def _many(self, points: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Strings, longest first, read in step: a transition of each per round."""
        n, longest = len(size), int(size[0])
        start, char = np.cumsum(size) - size, self._ids(points).astype(np.int64)
        extra = np.array([1, 2, 3, 4])[(points >= 0x80).astype(int) + (points >= 0x800) + (points >= 0x10000)]
        last = np.full((longest + 1, n), -1, np.int32)
        count = np.zeros((longest + 1, n), np.int32)
        state = np.zeros(n, np.int64)
        for i in range(longest):
            live = int(np.searchsorted(-size, -i, "left"))
            here = start[:live] + i
            c = char[here]
            known = np.flatnonzero(c)
            odd = np.flatnonzero(c == 0)
            count[i + 1, odd] = count[i, odd] + extra[here[odd]]
            state[odd] = 0
            at = self._next(state[known], c[known])
            state[known] = at
            token, left = self.out[at], np.arange(len(known))
            while len(left):
                lane, t = known[left], token[left]
                begin = i + 1 - self.length[t]
                before = last[begin, lane].astype(np.int64)
                good = before < 0
                good[~good] = self.fits(before[~good], t[~good])
                lanes = lane[good]
                last[i + 1, lanes] = t[good]
                count[i + 1, lanes] = count[begin[good], lanes] + 1
                token[left[~good]] = self.shorter[t[~good]]
                left = left[~good]
        return count[size, np.arange(n)].astype(np.int64), self._first_alone(last, size)

    def _first_alone(self, last: np.ndarray, size: np.ndarray) -> np.ndarray:
        """Walks back from the end to each string's first token."""
        lane, at = np.arange(len(size)), size.copy()
        out = np.zeros(len(size), bool)
        while len(lane):
            t = last[at[lane], lane]
            step = np.where(t < 0, 1, self.length[np.maximum(t, 0)])
            at[lane] -= step
            done = at[lane] == 0
            out[lane[done]] = step[done] == 1
            lane = lane[~done]
        return out

    def _one(self, text: str) -> tuple[int, bool]:
        """One string by itself, in memory that does not grow with its tokens' number of states."""
        if not hasattr(self, "_step"):
            self._step = dict(zip(self.key.tolist(), self.to.tolist()))
            self._lists = [x.tolist() for x in (self.fail, self.out, self.shorter, self.length)]
            self._pairs: dict[int, bool] = {}
        fail, out, shorter, length = self._lists
        points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        extra = np.array([1, 2, 3, 4])[(points >= 0x80).astype(int) + (points >= 0x800) + (points >= 0x10000)].tolist()
        last, count, state, width, step = [-1], [0], 0, self.width, self._step
        for i, c in enumerate(self._ids(points).tolist()):
            if not c:
                state = 0
                last.append(-1)
                count.append(count[i] + extra[i])
                continue
            while state and state * width + c not in step:
                state = fail[state]
            state = step.get(state * width + c, 0)
            t = out[state]
            while True:
                begin = i + 1 - length[t]
                before = last[begin]
                if before < 0:
                    break
                key = before * self.size + t
                good = self._pairs.get(key)
                if good is None:
                    if len(self._pairs) > MAX_PAIRS:
                        self._pairs.clear()
                    good = self._pairs[key] = bool(self._compatible(np.array([before]), np.array([t]))[0])
                if good:
                    break
                t = shorter[t]
            last.append(t)
            count.append(count[begin] + 1)
        at = len(text)
        while at:
            size = 1 if last[at] < 0 else length[last[at]]
            at -= size
        return count[-1], size == 1
