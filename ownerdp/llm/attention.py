"""A small causal self-attention model over subword ids in numpy: one layer, trained by hand-written gradients, and its scorer.

Its inputs are the subwords of a text, its targets the tokens that follow: words, and the end. Where a token begins, the layer
predicts its class from the subwords before it. A token's symbol is its first subword, together with whether more follow; the
frequent symbols, many of them whole words, are classes of their own, the others fall into clusters by what stands around them.
Within a class a symbol has its share of the counts; how a longer word goes on is left to ``spelling``.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

DIM, HIDDEN = 16, 32
#: Inputs that a window holds, and positions whose next token it scores: windows overlap by WINDOW - STRIDE inputs.
WINDOW, STRIDE = 32, 24
#: Symbols that are a class of their own, the most frequent ones, and clusters of the others.
SINGLE, CLUSTERS = 64, 64
CLASSES = SINGLE + CLUSTERS
#: Logits are held within these limits, so that neither an exponential nor a sum of them overflows or vanishes.
LOGIT = 60
#: Windows of a training step that go through the layer together.
TOGETHER = 32


@dataclass
class Vocabulary:
    """Fixed parts, from counts over all training text. n ids, the end among them, have 2n symbols: i, and n + i where the word goes on.

    embedding: of each id; starts: ids that begin a token; of_class and log_within: of each symbol its class and
    log P(symbol | class); log_class: log P(class).
    """

    embedding: np.ndarray
    starts: np.ndarray
    of_class: np.ndarray
    log_within: np.ndarray
    log_class: np.ndarray


def symbols(ids: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """The symbol of the token that begins at each place of texts laid end to end, each closed by the end; -1 where none begins."""
    goes_on = np.append(~starts[ids[1:]], False)
    return np.where(starts[ids], ids + len(starts) * goes_on, -1)


def _shares(m: np.ndarray) -> np.ndarray:
    """How much more often each row has each neighbour than all rows have, as clipped logarithms."""
    m = m.astype(float)
    return np.clip(np.log((m + 0.5) / (m.sum(axis=1, keepdims=True) + 0.5 * m.shape[1]) / ((m.sum(axis=0) + 0.5) / (m.sum() + 0.5 * m.shape[1]))), -4, 4)


def _clusters(x: np.ndarray, weight: np.ndarray, k: int, rng: np.random.Generator) -> np.ndarray:
    middle = x[rng.choice(len(x), k, replace=False, p=weight / weight.sum())]
    for _ in range(15):
        near = (((x**2).sum(1)[:, None] - 2 * x @ middle.T) + (middle**2).sum(1)).argmin(1)
        total = np.bincount(near, weight, k)
        moved = np.stack([np.bincount(near, weight * x[:, j], k) for j in range(x.shape[1])], axis=1)
        middle = np.where(total[:, None] > 0, moved / np.maximum(total, 1e-9)[:, None], middle)
    return near


def describe(counts: np.ndarray, around: np.ndarray, starts: np.ndarray, symbol_counts: np.ndarray, symbols_around: np.ndarray, seed: int = 7) -> Vocabulary:
    """counts: of each id; around: two halves, the counts of each id by the hash bucket of the id ahead of it and behind it; the same of symbols.

    The last id is the end."""
    rng = np.random.default_rng(seed)
    n, half = len(counts), around.shape[1] // 2
    features = np.concatenate([_shares(around[:, :half]), _shares(around[:, half:]), np.log1p(counts)[:, None] / 4], axis=1)
    seen = np.flatnonzero(counts > 0)
    embedding = rng.normal(size=(n, DIM))
    if len(seen) > DIM:
        weight = np.sqrt(counts[seen])
        centre = np.average(features[seen], axis=0, weights=weight)
        values, axes = np.linalg.eigh(np.cov(features[seen].T, aweights=weight) + 1e-6 * np.eye(features.shape[1]))
        top = np.argsort(values)[::-1][:DIM]
        embedding = np.clip((features - centre) @ axes[:, top] / np.sqrt(values[top]), -3, 3)
    possible = np.concatenate([starts, starts])
    possible[-1] = False  # nothing goes on after the end
    listed = np.flatnonzero(possible)
    listed = listed[np.argsort(-symbol_counts[listed], kind="stable")]
    of_class = np.full(2 * n, -1, np.int32)
    of_class[listed[:SINGLE]] = np.arange(min(SINGLE, len(listed)))
    rest = listed[SINGLE:]
    of_class[rest] = SINGLE + rest % CLUSTERS  # unseen symbols are spread evenly
    known = rest[symbol_counts[rest] > 0]
    if len(known) > CLUSTERS:
        half = symbols_around.shape[1] // 2
        x = np.concatenate([_shares(symbols_around[known][:, :half]), _shares(symbols_around[known][:, half:])], axis=1)
        of_class[known] = SINGLE + _clusters(x, np.sqrt(symbol_counts[known]), CLUSTERS, rng)
    log_within = np.zeros(2 * n)
    size, its = np.bincount(of_class[listed], minlength=CLASSES), np.bincount(of_class[listed], symbol_counts[listed], CLASSES)
    log_within[listed] = np.log((symbol_counts[listed] + 0.1) / (its + 0.1 * size)[of_class[listed]])
    log_class = np.log((its + 1) / (its.sum() + CLASSES))
    return Vocabulary(embedding.astype(np.float32), starts.astype(bool), of_class, log_within, log_class)


def initial(vocabulary: Vocabulary, seed: int = 11) -> dict[str, np.ndarray]:
    rng = np.random.default_rng(seed)
    draw = lambda a, b: (rng.normal(size=(a, b)) / np.sqrt(a)).astype(np.float32)
    return {
        "query": 0.3 * draw(DIM, DIM), "key": 0.3 * draw(DIM, DIM), "value": draw(DIM, DIM), "distance": np.zeros(WINDOW, np.float32),
        "own": draw(DIM, HIDDEN), "mixed": 1.5 * draw(DIM, HIDDEN), "hidden_bias": np.zeros(HIDDEN, np.float32),
        "out": 0.1 * draw(HIDDEN, CLASSES), "out_bias": vocabulary.log_class.astype(np.float32),
    }


_BACK = np.arange(WINDOW)[:, None] - np.arange(WINDOW)[None, :]
_BEHIND = np.where(_BACK < 0, WINDOW, _BACK).ravel()


def _weights_by_distance(distance: np.ndarray, back: np.ndarray) -> np.ndarray:
    """What a key's weight is multiplied by; nothing is left of keys behind the asking position."""
    return np.append(np.exp(np.clip(distance, -LOGIT / 2, LOGIT / 2)), distance.dtype.type(0)).take(np.where(back < 0, WINDOW, back))


def _exp(x: np.ndarray) -> np.ndarray:
    """In place."""
    x.clip(-LOGIT, LOGIT, out=x)
    return np.exp(x, out=x)


def _asked(asked: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Where tokens begin behind the positions of each window: (slots, windows, places). Only there does the layer predict, so only those positions
    ask: slots holds them for each window, as many as the fullest one has, and (windows, places) tell which slots are real."""
    windows, at = np.divmod(np.flatnonzero(asked), asked.shape[1])
    count = np.bincount(windows, minlength=len(asked))
    places = np.arange(len(windows)) - np.repeat(np.cumsum(count) - count, count)
    slots = np.zeros((len(asked), max(1, int(count.max(initial=0)))), np.int64)
    slots[windows, places] = at
    return slots, windows, places


def training_windows(documents: list[np.ndarray], vocabulary: Vocabulary) -> tuple[np.ndarray, np.ndarray]:
    """(inputs, goals), WINDOW wide: consecutive windows of each document, the end ahead of it. A goal is the class of the token that
    begins next, the end behind the text included; -1 where none begins. Every token is a goal once."""
    end = len(vocabulary.embedding) - 1
    inputs, goals = [], []
    for ids in documents:
        whole = np.concatenate([[end], ids, [end]]).astype(np.int64)
        its = symbols(whole, vocabulary.starts)[1:]
        size = -(-len(its) // WINDOW) * WINDOW
        x, y = np.full(size, end, np.int64), np.full(size, -1, np.int64)
        x[: len(its)] = whole[:-1]
        y[: len(its)] = np.where(its >= 0, vocabulary.of_class[its], -1)
        inputs.append(x.reshape(-1, WINDOW))
        goals.append(y.reshape(-1, WINDOW))
    if not inputs:
        return np.zeros((0, WINDOW), np.int64), np.zeros((0, WINDOW), np.int64)
    return np.concatenate(inputs), np.concatenate(goals)


def _one_behind(x: np.ndarray) -> np.ndarray:
    """Embeddings with a one behind each: weights times them also add up the weights, and a bias is a row of a matrix."""
    return np.concatenate([x, np.ones((*x.shape[:-1], 1), x.dtype)], axis=-1)


def _matrices(w: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """For embeddings with a one behind them: what an asking one's product with a key's is the logit of; from the asking one and from the mean of the
    keys to the hidden layer, which gets a one behind it too; from there to the classes. Keys and values are linear in the embeddings, so
    neither is made for each position."""
    kind = w["query"].dtype
    asks, from_own, from_mean = np.zeros((DIM + 1, DIM + 1), kind), np.zeros((DIM + 1, HIDDEN + 1), kind), np.zeros((DIM + 1, HIDDEN + 1), kind)
    asks[:DIM, :DIM] = w["query"] @ w["key"].T / np.sqrt(DIM)
    from_own[:DIM, :HIDDEN], from_own[DIM, :HIDDEN], from_own[DIM, HIDDEN] = w["own"], w["hidden_bias"], 1
    from_mean[:DIM, :HIDDEN] = w["value"] @ w["mixed"]
    return asks, from_own, from_mean, np.concatenate([w["out"], w["out_bias"][None]])


def _hidden(x: np.ndarray, own: np.ndarray, near: np.ndarray, matrices: tuple) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """x: (windows, keys, DIM + 1); own: the asking ones of each window; near: the keys' weights by distance for each. Returns the keys'
    weights and, in rows, their sums, the means of the keys, and the hidden layer."""
    asks, from_own, from_mean, _ = matrices
    rows = own.reshape(-1, DIM + 1)
    p = _exp((rows @ asks).reshape(own.shape) @ x.transpose(0, 2, 1))
    p *= near
    mean = (p @ x).reshape(-1, DIM + 1)
    total = mean[:, DIM:].copy()
    mean /= total
    h = rows @ from_own
    h += mean @ from_mean
    return p, total, mean, np.maximum(h, 0, out=h)


def _classes(h: np.ndarray, out: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of hidden layers exp(logits) of all classes, and their sums."""
    z = _exp(h @ out)
    return z, z @ np.ones(CLASSES, z.dtype)


def _sums(matrices: tuple, by_distance: np.ndarray, x: np.ndarray, slots: np.ndarray, goals: np.ndarray) -> list:
    """Over all goals of some windows (slots, and a class or -1 for each slot) the sum of the losses in nats, and of the gradients of the matrices and
    of by_distance's logarithm. x: (windows, WINDOW, DIM + 1)."""
    *_, from_mean, out = matrices
    own = x.reshape(-1, DIM + 1).take(slots + WINDOW * np.arange(len(x))[:, None], axis=0)
    p, total, mean, h = _hidden(x, own, by_distance.take(slots, axis=0), matrices)
    goal, all_rows = goals.ravel(), np.arange(goals.size)
    z, every = _classes(h, out)
    its, real = z[all_rows, goal], goal >= 0
    loss = -float(np.log(its[real] / every[real] + 1e-30).sum())
    z *= np.where(real, 1 / every, 0).astype(z.dtype)[:, None]
    z[all_rows, goal] -= real
    du = z @ out.T  # also of the one behind the hidden layer, which nothing asks for
    du *= np.sign(h)
    blame = du @ from_mean.T
    blame /= total
    blame[:, DIM] = -np.einsum("rd,rd->r", blame, mean)  # the weighted mean of what each key is blamed for
    ds = blame.reshape(own.shape) @ x.transpose(0, 2, 1)
    ds *= p
    rows, placed = own.reshape(-1, DIM + 1), np.eye(WINDOW, dtype=x.dtype).take(slots.ravel(), axis=0)
    return [loss, rows.T @ (ds @ x).reshape(-1, DIM + 1), rows.T @ du, mean.T @ du, h.T @ z, placed.T @ ds.reshape(-1, WINDOW)]


def _gradient(w: dict[str, np.ndarray], sums: list, m: int) -> dict[str, np.ndarray]:
    """Of the weights, from the sums over m goals."""
    of_asks, of_own, of_mean, of_out, by_pair = (x / x.dtype.type(m) for x in sums[1:])
    of_asks, of_mean = of_asks[:DIM, :DIM] / of_asks.dtype.type(np.sqrt(DIM)), of_mean[:DIM, :HIDDEN]
    return {
        "query": of_asks @ w["key"], "key": of_asks.T @ w["query"], "value": of_mean @ w["mixed"].T, "distance": np.bincount(_BEHIND, by_pair.ravel())[:WINDOW].astype(by_pair.dtype),
        "own": of_own[:DIM, :HIDDEN], "mixed": w["value"].T @ of_mean, "hidden_bias": of_own[DIM, :HIDDEN], "out": of_out[:HIDDEN], "out_bias": of_out[HIDDEN],
    }


def _slots_of(goal: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of windows of goals the slots, the goal of each (-1 for none), and how many each window has."""
    slots, windows, places = _asked(goal >= 0)
    goals = np.full(slots.shape, -1)
    goals[windows, places] = goal[windows, slots[windows, places]]
    return slots, goals, np.bincount(windows, minlength=len(goal))


def loss_and_gradient(w: dict[str, np.ndarray], x: np.ndarray, goal: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
    """Mean loss in nats over the goals and its gradient. x: (windows, WINDOW, DIM) embeddings; goal: classes, -1 for none."""
    slots, goals, counts = _slots_of(goal)
    sums, m = _sums(_matrices(w), _weights_by_distance(w["distance"], _BACK), _one_behind(x), slots, goals), max(1, int(counts.sum()))
    return sums[0] / m, _gradient(w, sums, m)


class Trainer:
    """Adam steps over windows, from given weights; its moments stay from call to call. All weights are views of one row of numbers."""

    def __init__(self, w: dict[str, np.ndarray], vocabulary: Vocabulary, rate: float, batch: int = 128):
        self.flat = np.concatenate([v.ravel() for v in w.values()]).astype(np.float32)
        edges = np.cumsum([0, *(v.size for v in w.values())])
        self.w = {k: self.flat[a:b].reshape(v.shape) for (k, v), a, b in zip(w.items(), edges[:-1], edges[1:], strict=True)}
        self.vocabulary, self.rate, self.batch, self.steps, self.losses = vocabulary, rate, batch, 0, []
        self.first, self.second = np.zeros_like(self.flat), np.zeros_like(self.flat)
        self.embedding = _one_behind(vocabulary.embedding)

    def run(self, inputs: np.ndarray, goals: np.ndarray, seed: int = 0) -> None:
        """One pass over the windows in a random order. Windows of a step that ask about as often go through the layer together: few empty slots."""
        order = np.random.default_rng(seed).permutation(len(inputs))
        slots, goals, counts = _slots_of(goals)
        for i in range(0, len(order), self.batch):
            rows = order[i : i + self.batch]
            rows = rows[np.argsort(counts[rows], kind="stable")]
            matrices, by_distance, sums = _matrices(self.w), _weights_by_distance(self.w["distance"], _BACK), None
            for j in range(0, len(rows), TOGETHER):
                some = rows[j : j + TOGETHER]
                width = max(1, int(counts[some[-1]]))
                more = _sums(matrices, by_distance, self.embedding.take(inputs[some], axis=0), slots[some, :width], goals[some, :width])
                sums = more if sums is None else [a + b for a, b in zip(sums, more, strict=True)]
            m = max(1, int(counts[rows].sum()))
            self.losses.append(sums[0] / m)
            g = _gradient(self.w, sums, m)
            self.steps += 1
            d = np.concatenate([g[k].ravel() for k in self.w])
            self.first += np.float32(0.1) * (d - self.first)
            self.second += np.float32(0.01) * (d * d - self.second)
            step = np.sqrt(self.second / np.float32(1 - 0.99**self.steps))
            step += np.float32(1e-8)
            self.flat -= np.float32(self.rate / (1 - 0.9**self.steps)) * self.first / step


class Scorer:
    """Scores whole documents: windows that ask about as often go through the layer together."""

    def __init__(self, w: dict[str, np.ndarray], vocabulary: Vocabulary):
        self.vocabulary = vocabulary
        x = _one_behind(vocabulary.embedding)
        self.embedding = np.concatenate([x, np.zeros((1, DIM + 1), x.dtype)])  # the last row is no key: whatever its weight, it adds nothing
        self.matrices = _matrices(w)
        back = np.arange(STRIDE)[:, None] + (WINDOW - STRIDE) - np.arange(WINDOW)[None, :]
        self.by_distance = _weights_by_distance(w["distance"], back)

    def log10(self, documents: list[np.ndarray], chunk: int = 128) -> np.ndarray:
        """Of each document (ids) the log10 probability of the symbols of its tokens and its end."""
        none, ahead = len(self.embedding) - 1, WINDOW - STRIDE
        end = np.array([none - 1], np.int64)
        lengths = np.array([len(d) + 1 for d in documents], np.int64)  # the end stands ahead of each document
        if not len(lengths):
            return np.zeros(0)
        flat = np.concatenate([x for d in documents for x in (end, d)] + [end])
        its = symbols(flat, self.vocabulary.starts)[1:]  # what begins behind each place
        begins = its >= 0
        document = np.repeat(np.arange(len(lengths)), lengths)
        total = np.bincount(document[begins], self.vocabulary.log_within[its[begins]], len(lengths))
        classes = np.append(np.where(begins, self.vocabulary.of_class[its], -1), np.full(WINDOW, -1))
        flat = np.concatenate([np.full(ahead, end[0]), flat, np.full(WINDOW, end[0])])  # a place p is at p + ahead
        begin = np.cumsum(lengths) - lengths
        windows = -(-lengths // STRIDE)
        owner = np.repeat(np.arange(len(lengths)), windows)
        scored = begin[owner] + (np.arange(len(owner)) - np.repeat(np.cumsum(windows) - windows, windows)) * STRIDE
        limit = begin[owner] + lengths[owner]
        upto = np.append(0, np.cumsum(begins))
        order = np.argsort(upto[np.minimum(scored + STRIDE, limit)] - upto[scored], kind="stable")
        scored, limit, owner = scored[order], limit[order], owner[order]
        of_window = np.zeros(len(owner))
        for i in range(0, len(owner), chunk):
            part = slice(i, i + chunk)
            ids = flat.take(scored[part, None] + np.arange(WINDOW))
            outside = np.flatnonzero(scored[part] - ahead < begin[owner[part]])  # windows that reach ahead of their document
            ids[outside, :ahead] = np.where(scored[part][outside, None] - ahead + np.arange(ahead) < begin[owner[part][outside], None], none, ids[outside, :ahead])
            here = scored[part, None] + np.arange(STRIDE)
            goal = classes.take(here)
            goal[here >= limit[part, None]] = -1
            slots, window, place = _asked(goal >= 0)
            x = self.embedding.take(ids, axis=0)
            at = np.arange(len(x))[:, None]
            own = x.reshape(-1, DIM + 1).take(slots + (WINDOW * at + ahead), axis=0)
            *_, h = _hidden(x, own, self.by_distance.take(slots, axis=0), self.matrices)
            real = window * slots.shape[1] + place
            z, every = _classes(h, self.matrices[-1])
            log_p = np.log(z[real, goal[window, slots[window, place]]] / every[real])
            of_window[part] = np.bincount(window, log_p, len(x))
        return (total + np.bincount(owner, of_window, len(lengths))) / np.log(10)
