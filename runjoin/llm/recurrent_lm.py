"""Document log-likelihood by a gated recurrent language model with a class-factored softmax, in numpy."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterable, Iterator
from functools import partial
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, fold, table, text_rows

#: The network's words: CLASSES x MEMBERS, by corpus frequency; the last one stands for all others.
CLASSES, MEMBERS = 32, 32
VOCABULARY = CLASSES * MEMBERS
#: Width of the word vectors' gates, steps of a window, lanes that go through windows together.
HIDDEN, WINDOW, LANES = 24, 16, 512
#: Frequent words whose counts every worker holds; the counts of all others are joined.
HELD_WORDS = 1 << 16
#: Documents whose pieces may enter the first fit on the driver, pieces that do and words of one (then every training
#: document is learned from whole, where it lies, its state carried from its first word to its last).
START_DOCS, START_PIECES, PIECE = 400, 1000, 1024
#: Words that a task lays out or scores at a time, documents it scores at a time.
ROOM, ROWS = 1 << 20, 8192
END = b""
_NAMES = ("embed", "update", "bias", "class_w", "class_b", "word_w", "word_b")


def tokens(text: str) -> list[bytes]:
    """Words with A to Z lower-cased, then one end."""
    return [*text.encode().lower().split(), END]


def fresh(seed: int = 5) -> dict[str, np.ndarray]:
    rng = np.random.default_rng(seed)
    draw = lambda *shape, scale: rng.normal(0, scale, shape).astype(np.float32)
    return {
        "embed": draw(VOCABULARY, 3 * HIDDEN, scale=0.1),
        "update": draw(HIDDEN, 3 * HIDDEN, scale=HIDDEN**-0.5),
        "bias": np.zeros(3 * HIDDEN, np.float32),
        "class_w": draw(HIDDEN, CLASSES, scale=0.1),
        "class_b": np.zeros(CLASSES, np.float32),
        "word_w": draw(CLASSES, HIDDEN, MEMBERS, scale=0.1),
        "word_b": np.zeros((CLASSES, MEMBERS), np.float32),
    }


def _sigmoid(x: np.ndarray) -> np.ndarray:
    """In place."""
    np.negative(x, out=x)
    np.exp(x, out=x)
    x += 1
    return np.reciprocal(x, out=x)


def forward(model: dict[str, np.ndarray], ids: np.ndarray, state: np.ndarray, keep: bool = False) -> tuple[np.ndarray, tuple[np.ndarray, ...]]:
    """States after each step of a window. ids: (steps, lanes) words read; state: (lanes, HIDDEN) carried in. With ``keep``
    also what the steps held: states before, both gates, new states, products. Each lies by itself, as strided parts are slow."""
    steps, lanes, h = *ids.shape, HIDDEN
    read = (model["embed"] + model["bias"]).take(ids.reshape(-1), axis=0).reshape(steps, lanes, 3 * h)
    states = np.empty((steps + 1, lanes, h), np.float32)
    states[0] = state
    held = steps if keep else 1
    gates, fresh_states, agains = (np.empty((held, *x, lanes, h), np.float32) for x in ((2,), (), ()))
    both = np.empty((lanes, 3 * h), np.float32)
    for t in range(steps):
        k = t if keep else 0
        opened, new, product = gates[k], fresh_states[k], agains[k]
        np.matmul(states[t], model["update"], out=both)
        np.add(read[t, :, :h], both[:, :h], out=opened[0])
        np.add(read[t, :, h : 2 * h], both[:, h : 2 * h], out=opened[1])
        z, r = _sigmoid(opened)
        product[:] = both[:, 2 * h :]
        np.multiply(r, product, out=new)
        new += read[t, :, 2 * h :]
        np.tanh(new, out=new)
        after = np.subtract(states[t], new, out=states[t + 1])
        after *= z
        after += new
    return states[1:], (states[:-1], gates[:, 0], gates[:, 1], fresh_states, agains) if keep else ()


_ONES = np.ones(max(CLASSES, MEMBERS), np.float32)


def _weights(logits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """exp of the logits and their sums by row; the sums are a product with ones, much faster than short-row sums."""
    if logits.size and logits.max() > 60:
        logits -= logits.max(axis=1, keepdims=True)
    weights = np.exp(logits)
    return weights, weights @ _ONES[: logits.shape[1]]


def _column_sums(x: np.ndarray) -> np.ndarray:
    return np.ones(len(x), np.float32) @ x


def _by_class(kind: np.ndarray) -> Iterator[tuple[int, slice]]:
    """The part of each class that occurs, in sorted ``kind``."""
    ends = np.cumsum(np.bincount(kind, minlength=CLASSES)).tolist()
    for c, (begin, end) in enumerate(zip([0, *ends], ends, strict=False)):
        if end > begin:
            yield c, slice(begin, end)


def _class_order(targets: np.ndarray) -> np.ndarray:
    return np.argsort((targets // MEMBERS).astype(np.uint8), kind="stable")


def log_probs(model: dict[str, np.ndarray], states: np.ndarray, targets: np.ndarray) -> np.ndarray:
    """Natural log probability of each target word: its class, then itself in the class."""
    order = _class_order(targets)
    states, goal = states[order], targets[order]
    kind, member, row = goal // MEMBERS, goal % MEMBERS, np.arange(len(goal))
    weights, sums = _weights(states @ model["class_w"] + model["class_b"])
    share = weights[row, kind] / sums
    for c, own in _by_class(kind):
        weights, sums = _weights(states[own] @ model["word_w"][c] + model["word_b"][c])
        share[own] *= weights[row[: len(weights)], member[own]] / sums
    logs = np.empty_like(share)
    logs[order] = np.log(np.maximum(share, 1e-37))
    return logs


def gradients(model: dict[str, np.ndarray], ids: np.ndarray, targets: np.ndarray, state: np.ndarray, share_of: int | None = None) -> tuple[dict[str, np.ndarray], np.ndarray, float]:
    """Gradients through one window of the loss over ``share_of`` (the words counted, if not given), the state carried
    out, and the summed loss. Targets of -1 don't count."""
    out, held = forward(model, ids, state, keep=True)
    grads, loss = _backward(model, ids, targets, out, held, share_of or max(1, int((targets >= 0).sum())))
    return grads, out[-1], loss


def _backward(model: dict[str, np.ndarray], ids: np.ndarray, targets: np.ndarray, out: np.ndarray, held: tuple[np.ndarray, ...], over: int) -> tuple[dict[str, np.ndarray], float]:
    """Gradients and summed loss of what ``forward`` gave and held; lanes may be those of several windows, side by side."""
    before, z, r, new, again = held
    real = np.flatnonzero(targets.reshape(-1) >= 0)
    real = real[_class_order(targets.reshape(-1)[real])]
    goal = targets.reshape(-1)[real]
    states = out.reshape(-1, HIDDEN)[real]
    grads = {"word_w": np.zeros_like(model["word_w"]), "word_b": np.zeros_like(model["word_b"]), "embed": np.zeros_like(model["embed"])}
    kind, member = goal // MEMBERS, goal % MEMBERS
    row = np.arange(len(goal))
    slope, sums = _weights(states @ model["class_w"] + model["class_b"])
    share = slope[row, kind] / sums
    slope /= (sums * over)[:, None]
    slope[row, kind] -= 1 / over
    grads["class_w"], grads["class_b"] = states.T @ slope, _column_sums(slope)
    back = slope @ model["class_w"].T
    for c, own in _by_class(kind):
        mine = states[own]
        part, sums = _weights(mine @ model["word_w"][c] + model["word_b"][c])
        at = row[: len(mine)], member[own]
        share[own] *= part[at] / sums
        part /= (sums * over)[:, None]
        part[at] -= 1 / over
        np.matmul(mine.T, part, out=grads["word_w"][c])
        grads["word_b"][c] = _column_sums(part)
        back[own] += part @ model["word_w"][c].T
    loss = -float(np.log(np.maximum(share, 1e-37)).sum())
    full = np.zeros((ids.size, HIDDEN), np.float32)
    full[real] = back
    full = full.reshape(out.shape)
    # slopes of all steps at once; only what is carried back goes step by step
    shut = 1 - z
    at_z = before - new
    at_z *= z
    at_z *= shut
    at_new = new * new
    np.subtract(1, at_new, out=at_new)
    at_new *= shut
    at_r = np.subtract(1, r, out=shut)
    at_r *= r
    at_r *= again
    carried = np.zeros(out.shape[1:], np.float32)
    again_grads = np.empty((*ids.shape, 3 * HIDDEN), np.float32)
    new_grads = np.empty(out.shape, np.float32)
    back_through = np.ascontiguousarray(model["update"].T)
    for t in range(len(ids) - 1, -1, -1):
        d, d_new, a = full[t], new_grads[t], again_grads[t]
        d += carried
        np.multiply(d, at_new[t], out=d_new)
        np.multiply(d, at_z[t], out=a[:, :HIDDEN])
        np.multiply(d_new, at_r[t], out=a[:, HIDDEN : 2 * HIDDEN])
        np.multiply(d_new, r[t], out=a[:, 2 * HIDDEN :])
        np.matmul(a, back_through, out=carried)
        d *= z[t]
        carried += d
    grads["update"] = before.reshape(-1, HIDDEN).T @ again_grads.reshape(-1, 3 * HIDDEN)
    again_grads[..., 2 * HIDDEN :] = new_grads
    _add_by_word(grads["embed"], ids.reshape(-1), again_grads.reshape(-1, 3 * HIDDEN))
    grads["bias"] = _column_sums(grads["embed"])
    return grads, loss


def _add_by_word(sums: np.ndarray, ids: np.ndarray, rows: np.ndarray, many: int = 64) -> None:
    """Sums of rows by word; those of words with ``many`` rows or more as products with ones."""
    words = ids.astype(np.uint16)  # radix-sorted
    order = np.argsort(words, kind="stable")
    words, rows = words[order], rows[order]
    first = np.flatnonzero(np.append(True, words[1:] != words[:-1]))
    ends = np.append(first[1:], len(words))
    often = ends - first >= many
    ones = np.ones(int((ends - first).max()), np.float32)
    for a, b in zip(first[often].tolist(), ends[often].tolist(), strict=True):
        sums[words[a]] = ones[: b - a] @ rows[a:b]
    few = ~often
    if few.any():
        kept = rows[np.repeat(few, ends - first)]
        size = (ends - first)[few]
        sums[words[first[few]]] = np.add.reduceat(kept, np.cumsum(size) - size, axis=0)


class Learner:
    """Adam over windows of truncated backpropagation."""

    def __init__(self, model: dict[str, np.ndarray], rate: float) -> None:
        self.model, self.rate, self.steps = model, rate, 0
        self.first = {k: np.zeros_like(v) for k, v in model.items()}
        self.second = {k: np.zeros_like(v) for k, v in model.items()}

    def learn(self, streams: Iterable[np.ndarray], lanes: int = LANES) -> tuple[float, int]:
        """Go once through streams of word numbers; returns the summed loss and the words.

        A step is taken once an eighth of a full window has been heard, so the long streams left at the end take few. The
        weights stay as they are until then, so the windows of a step go forward one by one and back side by side.
        """
        total, words, heard = 0.0, 0, 0
        state = np.zeros((lanes, HIDDEN), np.float32)
        group: list[tuple] = []

        def step() -> float:
            one = group[0] if len(group) == 1 else (*(np.concatenate(x, axis=1) for x in zip(*(g[:3] for g in group), strict=True)), tuple(np.concatenate(x, axis=1) for x in zip(*(g[3] for g in group), strict=True)))
            grads, loss = _backward(self.model, *one, lanes * WINDOW)
            group.clear()
            self._step(grads)
            return loss

        for live, fresh, ids, goals in windows(streams, lanes):
            state[live[fresh]] = 0
            out, held = forward(self.model, ids, state[live], keep=True)
            state[live] = out[-1]
            group.append((ids, goals, out, held))
            n = int((goals >= 0).sum())
            words, heard = words + n, heard + n
            if heard >= lanes * WINDOW // 8:
                total, heard = total + step(), 0
        if group:
            total += step()
        return total, words

    def _step(self, grads: dict[str, np.ndarray]) -> None:
        self.steps += 1
        size = float(np.sqrt(sum(float(np.vdot(g, g)) for g in grads.values())))  # plain floats leave arrays at 32 bits
        scale = min(1.0, 1.0 / max(size, 1e-9))
        rate = self.rate * (1 - 0.99**self.steps) ** 0.5 / (1 - 0.9**self.steps)
        for k, g in grads.items():
            g = g * scale
            self.first[k] += 0.1 * (g - self.first[k])
            self.second[k] += 0.01 * (g * g - self.second[k])
            self.model[k] -= rate * self.first[k] / (np.sqrt(self.second[k]) + 1e-6)


def windows(streams: Iterable[np.ndarray], lanes: int = LANES, room: int = ROOM) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Streams laid on lanes: (live lanes, which of them begin a stream, words read, words to come), a window at a time.

    A lane goes through its stream from window to window (so its state can be carried) and then takes the next one. The
    first word read is an end; a target of -1 stands where a stream has ended. Only ``room`` words and the rests of the
    streams on lanes are held, and only one window is laid out, however long a stream is.
    """
    streams, span = iter(streams), np.arange(WINDOW)
    flat = np.zeros(0, np.int32)
    at, left = np.zeros(lanes, np.int64), np.zeros(lanes, np.int64)
    starts, lengths, taken, more = np.zeros(0, np.int64), np.zeros(0, np.int64), 0, True
    while True:
        idle = np.flatnonzero(left == 0)
        if len(idle) and taken == len(starts) and more:
            new, size = [], 0
            for x in streams:
                new.append(x)
                size += len(x)
                if size >= room:
                    break
            else:
                more = False
            busy = np.flatnonzero(left)
            rests = [flat[at[k] : at[k] + left[k] + 1] for k in busy]  # the word read next, and all to come
            sizes = np.array([*(len(x) for x in rests), *(len(x) + 1 for x in new)], np.int64)
            place = np.cumsum(sizes) - sizes
            first = np.zeros(1, np.int32)
            flat = np.concatenate([*rests, *(p for x in new for p in (first, x)), np.zeros(WINDOW + 1, np.int32)])
            at[busy] = place[: len(busy)]
            starts, lengths, taken = place[len(busy) :], sizes[len(busy) :] - 1, 0
        n = min(len(idle), len(starts) - taken)
        begun = idle[:n]
        at[begun], left[begun] = starts[taken : taken + n], lengths[taken : taken + n]
        taken += n
        live = np.flatnonzero(left)
        if not len(live):
            return
        where = span[:, None] + at[live]
        goals = np.where(span[:, None] < left[live], flat[where + 1], -1)
        yield live, np.isin(live, begun), flat[where], goals
        step = np.minimum(left, WINDOW)
        at += step
        left -= step


def long_first(streams: Iterable[np.ndarray], room: int = 4 * ROOM) -> Iterator[np.ndarray]:
    """Streams by falling length, ``room`` words at a time: long ones then don't go on alone for long."""
    held, size = [], 0
    for x in streams:
        held.append(x)
        size += len(x)
        if size >= room:
            yield from sorted(held, key=len, reverse=True)
            held, size = [], 0
    yield from sorted(held, key=len, reverse=True)


def score_streams(model: dict[str, np.ndarray], streams: list[np.ndarray], lanes: int = LANES) -> np.ndarray:
    """Natural log probability of every stream, its state carried from window to window until the stream ends."""
    out = np.zeros(len(streams))
    order = sorted(range(len(streams)), key=lambda i: -len(streams[i]))  # long ones first, so that they don't go on alone
    owner, begun = np.zeros(lanes, np.int64), 0
    state = np.zeros((lanes, HIDDEN), np.float32)
    group: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []  # words of few lanes are looked up together

    def add() -> None:
        states, goals, owners = (np.concatenate(x) for x in zip(*group, strict=True))
        group.clear()
        out[:] += np.bincount(owners, weights=log_probs(model, states, goals), minlength=len(out))

    heard = 0
    for live, fresh, ids, goals in windows((streams[i] for i in order), lanes):
        new = live[fresh]
        owner[new] = order[begun : begun + len(new)]
        begun += len(new)
        state[new] = 0
        states, _ = forward(model, ids, state[live])
        state[live] = states[-1]
        want = goals.reshape(-1)
        real = np.flatnonzero(want >= 0)
        group.append((states.reshape(-1, HIDDEN)[real], want[real], owner[live][real % len(live)]))
        heard += len(real)
        if heard >= lanes * WINDOW // 2:
            add()
            heard = 0
    if group:
        add()
    return out


def numbered(words: list[bytes]) -> dict[bytes, int]:
    """Places of an end (0) and of ``words``, the most frequent first; a word's number in the network is its place, cut by ``named``."""
    return {END: 0} | {w: i + 1 for i, w in enumerate(words)}


def placed(words: list[bytes], places: dict[bytes, int]) -> np.ndarray:
    """Places of words, ``len(places)`` for those without one."""
    return np.fromiter(map(places.get, words, repeat(len(places))), np.int32, len(words))


def named(places: np.ndarray, listed: int) -> np.ndarray:
    """Numbers in the network: the last stands for every word beyond it and for those without a place (``listed``)."""
    ids = np.minimum(places, VOCABULARY - 1)
    return ids if listed >= VOCABULARY - 1 else np.where(places == listed, np.int32(VOCABULARY - 1), ids)


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Partial word counts, given up whenever they get large."""
    held: Counter = Counter()

    def flush() -> pa.RecordBatch:
        made = pa.RecordBatch.from_arrays([pa.array(list(held), pa.binary()), pa.array(list(held.values()), pa.int64())], ["word", "n"])
        held.clear()
        return made

    for _, texts in text_rows(batches):
        for text in texts:
            held.update(tokens(text))
            if len(held) > 300_000:
                yield flush()
    yield flush()


def _learn(batches: Iterator[pa.RecordBatch], model: dict[str, np.ndarray], number: dict[bytes, int], rate: float) -> Iterator[pa.RecordBatch]:
    """Go on learning from all documents of a task; gives its weights times the words seen, and those, as one row."""
    learner = Learner({k: v.copy() for k, v in model.items()}, rate)
    streams = (named(placed(tokens(text), number), len(number)) for _, texts in text_rows(batches) for text in texts)
    _, seen = learner.learn(long_first(streams))
    if seen:
        flat = np.concatenate([learner.model[k].reshape(-1) for k in _NAMES]).astype(np.float64) * seen
        yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId()], pa.int64()), pa.array([seen], pa.int64()), pa.array([flat.tobytes()], pa.binary())], ["task", "seen", "weights"])


def _summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row for all rows of a task, added in their order."""
    total, seen, task = None, 0, 0
    for batch in batches:
        for t, n, raw in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            weights = np.frombuffer(raw)
            total = weights.copy() if total is None else total + weights
            seen, task = seen + n, t
    if total is not None:
        yield pa.RecordBatch.from_arrays([pa.array([task], pa.int64()), pa.array([seen], pa.int64()), pa.array([total.tobytes()], pa.binary())], ["task", "seen", "weights"])


def _averaged(learned: DataFrame, groups: int) -> tuple[np.ndarray, int] | None:
    """Weights of all tasks by the words each has seen: arrays are added in ``groups`` tasks, then in 8, then on the driver."""
    for n in (groups, min(8, groups)):
        learned = learned.repartitionById(n, F.pmod("task", F.lit(n)).cast("int")).sortWithinPartitions("task").mapInArrow(_summed, "task long, seen long, weights binary")
    rows = sorted(learned.collect(), key=lambda r: r["task"])  # 8 rows at most
    if not rows:
        return None
    return sum(np.frombuffer(r["weights"]) for r in rows) / sum(r["seen"] for r in rows), len(rows)


def _packed(flat: np.ndarray, like: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
    out, at = {}, 0
    for k in _NAMES:
        out[k] = flat[at : at + like[k].size].reshape(like[k].shape).astype(np.float32)
        at += like[k].size
    return out


def _score(batches: Iterator[pa.RecordBatch], model: dict[str, np.ndarray], places: dict[bytes, int], counts: np.ndarray, total: int, distinct: int, rare: tuple[int, int]) -> Iterator[pa.RecordBatch]:
    """Scores of whole documents; words without a place leave with their times, to be joined. ``counts``: by place."""
    scale, listed = np.log10(total + 0.5 * (distinct + 1)), len(places)
    # by place, and nothing for words without one
    logs_of = np.append(np.log10(counts + 0.5) - scale, 0.0)
    known = np.append(counts > 0, False)
    # the share of a word among those the network doesn't name
    shift = scale - np.log10(rare[0] + 0.5 * (rare[1] + 1))
    task, row, size = TaskContext.get().partitionId(), 0, 0
    ids, streams, fields = [], [], []

    def scored() -> pa.RecordBatch:
        logs = score_streams(model, streams) / np.log(10)
        c = list(zip(*fields, strict=True))
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.list_(pa.binary()), pa.list_(pa.int64())]
        made = pa.RecordBatch.from_arrays(
            [pa.array(ids, pa.int64()), *(pa.array(v, k) for v, k in zip(c, kinds, strict=True)), pa.array(logs)], ["doc_id", "row", "n_tokens", "n_known", "base", "rest", "words", "times", "logs"]
        )
        for held_rows in (ids, streams, fields):
            held_rows.clear()
        return made

    for batch, texts in text_rows(batches):
        for doc_id, text in zip(batch.column(0).to_pylist(), texts, strict=True):
            words = tokens(text)
            at = placed(words, places)
            ids.append(doc_id)
            streams.append(named(at, listed))
            parts = logs_of[at]
            other = streams[-1] == VOCABULARY - 1
            hidden = Counter(words[i] for i in np.flatnonzero(at == listed).tolist())
            rest = float(parts[other].sum()) + int(other.sum()) * shift
            fields.append((task << 36 | row, len(words), int(known[at].sum()), float(parts.sum()), rest, list(hidden), list(hidden.values())))
            row, size = row + 1, size + len(words)
            if len(ids) >= ROWS or size >= 2 * ROOM:  # the more texts, the fewer steps are taken for a long one alone
                yield scored()
                size = 0
    if ids:
        yield scored()


def pieces(ids: np.ndarray) -> list[np.ndarray]:
    return [ids[a : a + PIECE] for a in range(0, len(ids), PIECE)]


def _pieces(batches: Iterator[pa.RecordBatch], number: dict[bytes, int]) -> Iterator[pa.RecordBatch]:
    """All pieces of whole texts."""
    for batch, texts in text_rows(batches, 32):
        ids, nth, cut = [], [], []
        for doc_id, text in zip(batch.column(0).to_pylist(), texts, strict=True):
            for i, part in enumerate(pieces(named(placed(tokens(text), number), len(number)))):
                ids.append(doc_id)
                nth.append(i)
                cut.append(part)
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(nth, pa.int64()), pa.array(cut, pa.list_(pa.int32()))], ["doc_id", "nth", "ids"])


def _frequent(counts: DataFrame, words: int) -> DataFrame:
    """Rows that hold the ``words`` most frequent ones: a cut by bands of the logarithm, so few others come along."""
    named = counts.filter(F.octet_length("word") > 0)
    band = F.floor(F.log2("n") * 8)
    bands = sorted(((r[0], r[1]) for r in named.groupBy(band.alias("band")).count().collect()), reverse=True)  # 512 at most
    seen, cut = 0, 0
    for b, n in bands:
        seen, cut = seen + n, b
        if seen >= words:
            break
    return named.filter(band >= cut)


def lm_scores(docs: DataFrame, start_docs: int = START_DOCS, held_words: int = HELD_WORDS, start_pieces: int = START_PIECES) -> DataFrame:
    """log10 probabilities of every whole text by the network and by word counts.

    Columns: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score. Documents whose crc32(doc_id) mod 5
    is 1 are held out; all others are learned from: word counts are summed over all of them; the network starts from
    ``start_pieces`` pieces, drawn by hash from ``start_docs`` of them, fitted on the driver, then every task goes on over
    all training documents it reads, each from its first word to its last with its state carried, and the weights are
    averaged by words seen. So the weights (not the counts) depend on how the files are dealt to tasks. A word the
    network doesn't name has the probability of the last member times the word's share among such words (smoothed as
    the base), so scores are those of whole texts. Null and empty texts are an end alone; repeated rows are scored each;
    extra columns are ignored; an empty table gives no rows, a training part without rows leaves the network as it was drawn.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "lm")
    docs = docs.select("doc_id", "text")
    training = docs.filter(fold(F.col("doc_id")) != 1)
    counts = scratch.save(training.select("text").mapInArrow(_count, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n")), "counts")
    total, distinct = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count(F.lit(1))).first()
    top = _frequent(counts, held_words).orderBy(F.desc("n"), "word").limit(held_words).collect()  # HELD_WORDS rows at most
    ends = counts.filter(F.octet_length("word") == 0).first()
    places = numbered([bytes(r["word"]) for r in top])
    held = np.array([ends["n"] if ends else 0, *(r["n"] for r in top)], np.int64)
    number = dict(list(places.items())[: VOCABULARY - 1])
    in_network = held[: len(number)]
    rare = (total - int(in_network.sum()), distinct - int((in_network > 0).sum()))
    model = _started(training, number, in_network, rare[0], start_docs, start_pieces)
    learned = training.select("text").mapInArrow(partial(_learn, model=model, number=number, rate=0.004), "task long, seen long, weights binary")
    mean = _averaged(learned, max(1, int(spark.conf.get("spark.sql.shuffle.partitions"))))
    if mean:
        model = _packed(mean[0], model)
    run = partial(_score, model=model, places=places, counts=held, total=total, distinct=distinct, rare=rare)
    scored = scratch.save(docs.mapInArrow(run, "doc_id long, row long, n_tokens long, n_known long, base double, rest double, words array<binary>, times array<long>, logs double"), "scored")
    apart = scored.select("row", F.explode(F.arrays_zip("words", "times")).alias("x")).select("row", F.col("x.words").alias("word"), F.col("x.times").alias("k"))
    # counted words that the workers don't hold
    lasting = counts.filter(F.octet_length("word") > 0)
    if len(top) >= held_words:
        least = top[-1]
        lasting = lasting.filter((F.col("n") < least["n"]) | ((F.col("n") == least["n"]) & (F.col("word") > F.lit(bytes(least["word"])))))
    else:
        lasting = lasting.limit(0)
    scale = float(np.log10(total + 0.5 * (distinct + 1)))
    value = F.col("k") * (F.log10(F.coalesce("n", F.lit(0)) + 0.5) - scale)
    # hashed, not sorted: a partition of counted words is small beside one of texts
    joined = apart.join(lasting.hint("shuffle_hash"), "word", "left").groupBy("row").agg(F.sum(value).alias("more"), F.sum(F.when(F.col("n") > 0, F.col("k")).otherwise(0)).alias("more_known"))
    out = scored.join(joined, "row", "left")
    more = F.coalesce("more", F.lit(0.0))
    result = out.select(
        "doc_id",
        (fold(F.col("doc_id")) == 1).alias("held_out"),
        "n_tokens",
        (F.col("n_known") + F.coalesce("more_known", F.lit(0))).alias("n_known"),
        F.lit(total).cast("long").alias("train_tokens"),
        (F.col("base") + more).alias("base_score"),
        (F.col("logs") + F.col("rest") + more).alias("score"),
    )
    return scratch.last(result, "counts", "scored")


def _started(training: DataFrame, number: dict[bytes, int], in_network: np.ndarray, others: int, start_docs: int, start_pieces: int) -> dict[str, np.ndarray]:
    """The network after the first fit: output biases from counts, all else from a bounded sample of pieces."""
    first = training.filter("doc_id is not null").orderBy(F.xxhash64("doc_id"), "doc_id").limit(start_docs)
    cut = first.mapInArrow(partial(_pieces, number=number), "doc_id long, nth long, ids array<int>")
    rows = cut.orderBy(F.xxhash64("doc_id", "nth"), "doc_id", "nth").limit(start_pieces).collect()  # PIECE numbers each at most
    learner = Learner(fresh(), 0.01)
    if rows:
        base = np.append(in_network, max(0, others)) + 0.5
        base = np.concatenate([base[:-1], np.full(VOCABULARY - len(base), 1e-3), base[-1:]]).reshape(CLASSES, MEMBERS)
        learner.model["class_b"][:] = np.log(base.sum(axis=1) / base.sum())
        learner.model["word_b"][:] = np.log(base / base.sum(axis=1, keepdims=True))
        streams = [np.array(r["ids"], np.int32) for r in sorted(rows, key=lambda r: (r["doc_id"], r["nth"]))]
        learner.learn(streams * 4, 64)
    return learner.model


def op4_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document scored by counts and by the network."""
    return lm_scores(table(spark, sf_dir, "documents", "doc_id", "text"))
