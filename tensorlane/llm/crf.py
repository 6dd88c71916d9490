"""A linear-chain conditional random field over word shapes, in numpy.

A word's shape is a small number: how many digits it has, whether it has letters, an at
sign, a plus sign, how many dots and dashes.  Words without digit, at or plus sign all
share shape 0.  Scores of a label: its weights for the shapes of the word, the one before
and the one after, and a weight for each pair of neighbouring labels.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

KINDS = ("email", "ip", "card", "phone")
LABELS = ("O", *(f"{p}-{k}" for k in KINDS for p in "BI"))
DIGIT_STEPS = np.array([1, 4, 7, 9, 12, 20])
N_SHAPES = (len(DIGIT_STEPS) + 1) * 2 * 2 * 2 * 4 * 3

PAST, EDGE = -1, -2


def shape_ids(words: list[bytes]) -> np.ndarray:
    """Shape number of each word; 0 for words without digit, at or plus sign."""
    if not words:
        return np.zeros(0, np.int64)
    data = np.frombuffer(b"".join(words), np.uint8)
    ends = np.cumsum([len(w) for w in words])

    def count(mask: np.ndarray) -> np.ndarray:
        total = np.concatenate([[0], np.cumsum(mask)])
        return np.diff(total[np.concatenate([[0], ends])])

    digit = count((data >= 48) & (data <= 57))
    letter = count(((data | 32) >= 97) & ((data | 32) <= 122) | (data >= 128))
    at, plus = count(data == 64), count(data == 43)
    # a full stop at the end of a word is punctuation, not part of its shape
    last = np.array([w[-1:] == b"." for w in words])
    dots = np.minimum(count(data == 46) - last, 3)
    dashes = np.minimum(count((data == 45) | (data == 40) | (data == 41)), 2)
    step = np.searchsorted(DIGIT_STEPS, digit, "right")
    shape = ((((step * 2 + (letter > 0)) * 2 + (at > 0)) * 2 + (plus > 0)) * 4 + dots) * 3 + dashes
    return np.where((digit > 0) | (at > 0) | (plus > 0), shape, 0)


@dataclass
class ChainModel:
    here: np.ndarray  #: shapes x labels
    before: np.ndarray
    after: np.ndarray
    step: np.ndarray  #: labels x labels, from -> to

    def scores(self, shapes: np.ndarray) -> np.ndarray:
        """Label scores of padded sequences (rows of shape numbers; ``PAST`` beyond the end, ``EDGE`` for a word known to be O)."""
        safe = np.maximum(shapes, 0)
        left = np.pad(safe[:, :-1], ((0, 0), (1, 0)))
        right = np.pad(safe[:, 1:], ((0, 0), (0, 1)))
        return self.here[safe] + self.before[left] + self.after[right]

    def forced_gap(self, side: int) -> bool:
        """Whether a word amid ``side`` words of shape 0 to either side (and neighbours of shape 0 for all of
        them) is O on every best path, whatever the labels beyond, so that it cuts a sequence in two."""
        plain = self.here[0] + self.before[0] + self.after[0]
        k = len(plain)
        # best sums up to the middle word, from any label before the run or from the text's start
        ways = np.concatenate([np.where(np.eye(k, dtype=bool), 0.0, -np.inf), np.full((1, k), np.nan)])
        onward = [self.step + plain, (self.step + plain[:, None]).T]
        sums = []
        for move in onward:
            now = (ways[:k, :, None] + move).max(1)
            now = np.concatenate([now, plain[None]])
            for _ in range(side):
                now = (now[:, :, None] + move).max(1)
            sums.append(now)
        into, out = sums[0], sums[1] - plain
        both = into[:, None, :] + out[None, :, :]
        return bool((both[..., 0] > both[..., 1:].max(-1) + 1e-9).all())

    def viterbi(self, shapes: np.ndarray) -> np.ndarray:
        """Best label of every place, all sequences at once; O beyond their ends."""
        score = self.scores(shapes)
        score[shapes == EDGE, 1:] = -np.inf
        n, length, k = score.shape
        best, back = score[:, 0], np.zeros((n, length, k), np.int8)
        for t in range(1, length):
            ways = best[:, :, None] + self.step
            back[:, t] = ways.argmax(1)
            step = np.take_along_axis(ways, back[:, t][:, None, :].astype(np.int64), 1)[:, 0] + score[:, t]
            live = shapes[:, t] != PAST
            best = np.where(live[:, None], step, best)
            back[:, t] = np.where(live[:, None], back[:, t], np.arange(k))
        out = np.zeros((n, length), np.int64)
        out[:, -1] = best.argmax(1)
        for t in range(length - 1, 0, -1):
            out[:, t - 1] = np.take_along_axis(back[:, t], out[:, t][:, None], 1)[:, 0]
        return np.where(shapes >= 0, out, 0)


def _logsumexp(x: np.ndarray, axis: int) -> np.ndarray:
    m = x.max(axis, keepdims=True)
    return (m + np.log(np.exp(x - m).sum(axis, keepdims=True))).squeeze(axis)


def fit(shapes: np.ndarray, labels: np.ndarray, steps: int = 120, penalty: float = 0.2, rate: float = 0.15) -> ChainModel:
    """Conditional maximum likelihood with a quadratic penalty, by Adam over the whole table."""
    k = len(LABELS)
    n, length = shapes.shape
    live = shapes >= 0
    model = ChainModel(*[np.zeros((N_SHAPES, k)) for _ in range(3)], np.zeros((k, k)))
    weights = [model.here, model.before, model.after, model.step]
    mean, square = [np.zeros_like(w) for w in weights], [np.zeros_like(w) for w in weights]
    safe = np.maximum(shapes, 0)
    left, right = np.pad(safe[:, :-1], ((0, 0), (1, 0))), np.pad(safe[:, 1:], ((0, 0), (0, 1)))
    truth = np.eye(k)[labels] * live[..., None]
    both = live[:, 1:] & live[:, :-1]
    pairs = np.einsum("nti,ntj->ij", truth[:, :-1], truth[:, 1:] * both[..., None])
    for i in range(1, steps + 1):
        score = model.scores(shapes)
        fore, rear = np.zeros_like(score), np.zeros_like(score)
        fore[:, 0] = score[:, 0]
        for t in range(1, length):
            fore[:, t] = np.where(live[:, t, None], _logsumexp(fore[:, t - 1][:, :, None] + model.step, 1) + score[:, t], fore[:, t - 1])
        for t in range(length - 2, -1, -1):
            rear[:, t] = np.where(live[:, t + 1, None], _logsumexp(model.step + (rear[:, t + 1] + score[:, t + 1])[:, None, :], 2), 0)
        total = _logsumexp(fore[:, -1], 1)
        node = np.exp(fore + rear - total[:, None, None]) * live[..., None]
        edge = np.exp(fore[:, :-1, :, None] + model.step + (score + rear)[:, 1:, None, :] - total[:, None, None, None]) * both[..., None, None]
        miss = node - truth
        grads = []
        for at in (safe, left, right):
            g = np.zeros((N_SHAPES, k))
            np.add.at(g, at[live], miss[live])
            grads.append(g)
        grads.append(edge.sum((0, 1)) - pairs)
        for w, g, m, s in zip(weights, grads, mean, square, strict=True):
            g = g / n + penalty * w / 100
            m += 0.1 * (g - m)
            s += 0.001 * (g * g - s)
            w -= rate * (m / (1 - 0.9**i)) / (np.sqrt(s / (1 - 0.999**i)) + 1e-8)
    return model


def labelled_sentences(n: int = 400, seed: int = 11) -> list[list[tuple[str, str]]]:
    """The small labelled table: made sentences of (word, label), with look-alikes that are nothing personal."""
    rng = np.random.default_rng(seed)

    def digits(k: int) -> str:
        return "".join(map(str, rng.integers(0, 10, k)))

    def letters(k: int) -> str:
        return "".join(chr(97 + c) for c in rng.integers(0, 26, k))

    def one(*ways):
        return ways[rng.integers(len(ways))]

    def email() -> list[str]:
        name = one(letters(5), f"{letters(4)}.{letters(5)}", f"{letters(6)}.{digits(2)}", f"{letters(3)}_{digits(3)}", f"{letters(4)}+{letters(3)}")
        return [f"{name}@{one('mail', 'post', letters(5))}{one('', digits(1))}.{one('example.com', 'example.org', letters(4) + '.net')}"]

    def ip() -> list[str]:
        return [".".join(str(rng.integers(1, 256)) for _ in range(4))]

    def card() -> list[str]:
        return one([digits(16)], [digits(4) for _ in range(4)], ["-".join(digits(4) for _ in range(4))], [digits(15)])

    def phone() -> list[str]:
        a, b, c = digits(3), digits(3), digits(4)
        return one([f"+{digits(1)}", f"({a})", f"{b}-{c}"], [f"+{digits(2)}", a, b, c], [f"+{digits(11)}"], [f"({a})", f"{b}-{c}"], [f"{a}-{b}-{c}"])

    def nothing() -> list[str]:
        hexes = "".join("0123456789abcdef"[c] for c in rng.integers(0, 16, one(18, 20, 40)))
        return one(
            [digits(one(1, 2, 3, 4))], [f"{digits(4)}-{digits(2)}-{digits(2)}"], [f"{digits(1)}.{digits(1)}.{digits(1)}"], [f"{digits(2)}:{digits(2)}"],
            [f"password={hexes}"], [f'"{hexes}"'], [f"{letters(3)}{digits(2)}"], [f"{digits(3)},{digits(3)}"], [f"{digits(2)}.{digits(2)}"], [f"@{letters(5)}"],
            ["c++"], ["+"], [digits(one(5, 6, 8))], [f"{letters(2).upper()}{digits(1)}{letters(2).upper()}{digits(2)}{letters(2)}"], [f"{digits(3)}-{digits(4)}"], [digits(4), digits(4)],
            [digits(one(24, 30))], [f"{digits(2)}.{digits(3)}.{digits(2)}"],
        )

    makers = {"email": email, "ip": ip, "card": card, "phone": phone, "O": nothing}
    table = []
    for _ in range(n):
        sentence: list[tuple[str, str]] = []
        for _ in range(one(1, 2, 2, 3)):
            sentence += [(letters(rng.integers(1, 9)), "O") for _ in range(rng.integers(1, 6))]
            kind = one("email", "ip", "card", "phone", "O", "O", "O", "O")
            words = makers[kind]()
            if rng.random() < 0.25:
                words[-1] += one(".", ",")
            sentence += [(w, "O" if kind == "O" else f"{'I' if i else 'B'}-{kind}") for i, w in enumerate(words)]
        sentence += [(letters(rng.integers(1, 9)), "O") for _ in range(rng.integers(1, 6))]
        table.append(sentence)
    return table


def padded(sentences: list[list[tuple[str, str]]]) -> tuple[np.ndarray, np.ndarray]:
    longest = max(map(len, sentences))
    shapes, labels = np.full((len(sentences), longest), -1), np.zeros((len(sentences), longest), np.int64)
    for i, s in enumerate(sentences):
        shapes[i, : len(s)] = shape_ids([w.encode() for w, _ in s])
        labels[i, : len(s)] = [LABELS.index(y) for _, y in s]
    return shapes, labels


def trained(n: int = 240, seed: int = 11) -> ChainModel:
    return fit(*padded(labelled_sentences(n, seed)))
