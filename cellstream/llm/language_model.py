"""Language-model scoring: a gated recurrent network in numpy with a class-factored output.

Counts of all training tokens come first, from all training documents: of slices of texts in Arrow, then by Spark's own
aggregation (one exchange by word; it spills, so no vocabulary is too large). They give the base score and the model's vocabulary: the VOCABULARY most frequent words, in classes of
CLASS words by rank, and one class more for all other words. P(word) is P(class | state) times P(word | class, state);
in the last class, the second factor is (c + 1) / (n + v + 1) with the class's own totals, so that the
probabilities of all words, and one unseen word, sum to 1.

Training: truncated backpropagation through SPAN steps, states carried from one span to the next, Adam. It is data-parallel:
in each of ROUNDS rounds its part of the documents is dealt by hash to shards of about SHARD bytes, as many as they need; each
shard trains a copy of the network on its documents, in the order of their hashes, and the copies are averaged, weighted by
their tokens, in a tree of FAN copies a task. So the result follows the documents alone, not how the table is cut into
files or partitions; the driver gets one network. Every training document gives gradients, once: in the round that its hash
modulo ROUNDS names. Output biases start from the counts of all of them.

Scoring: documents run in LANES side by side, a lane taking the next one when it is done; the state is set
to zero at a document's start and carried across windows until its end, so that whole documents are scored.

Texts are split, lower-cased, counted and numbered in Arrow, a slice of texts at a time; no word becomes a Python object.
Counts of frequent words travel as a list of at most HEAD words. Rarer words leave the task as (row,
word, times) and meet their counts in a join, so that a vocabulary of any size is exact.

Defined results: null and empty texts are the end token alone; without training tokens every count is 0 and
the network is the initial one; repeated rows are scored each.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

VOCABULARY, CLASS, HEAD = 2048, 64, 300_000
EMBEDDED, STATE = 16, 24
SPAN, TRAIN_LANES, LANES, RATE = 20, 128, 256, 0.006
ROUNDS, SHARD, FAN = 2, 16_000_000, 32
#: Steps that are scored at once.
WINDOW = 64
#: Tasks that shards are dealt to at most.
TASKS = 10_000
#: Bytes of text that are scored at once, about.
TOGETHER = 6_000_000
#: Bytes of text whose words are counted at once, about.
COUNTED = 6_000_000


def word_list(text: str | None) -> list[bytes]:
    """Words in lower case (A-Z only) and the end, named by a line feed, which no word holds."""
    w = text.encode("utf-8", "surrogatepass").lower().split() if text else []
    w.append(b"\n")
    return w


def words_of(column):
    """The words of an Arrow array of texts, as `word_list` has them but without ends: all of them (binary), and how many
    each text holds."""
    import numpy as np
    import pyarrow as pa
    import pyarrow.compute as pc

    parts = pc.ascii_split_whitespace(pc.ascii_lower(pc.fill_null(column, "")))
    flat, n = parts.flatten(), pc.list_value_length(parts).to_numpy(zero_copy_only=False).astype(np.int64)
    full = pc.greater(pc.binary_length(flat), 0)  # white space at a text's edge leaves an empty part
    if not pc.all(full, min_count=0).as_py():
        n = np.bincount(np.repeat(np.arange(len(n)), n)[full.to_numpy(zero_copy_only=False)], minlength=len(n))
        flat = flat.filter(full)
    return flat.cast(pa.large_binary() if pa.types.is_large_string(flat.type) else pa.binary()), n


def numbers_of(words, n, known, other: int, end: int):
    """Ids of words (their places in the array known, `other` if not there) with an end after each text's n words, and
    where each text starts."""
    import numpy as np
    import pyarrow.compute as pc

    found = pc.fill_null(pc.index_in(words, value_set=known.cast(words.type)), other).to_numpy(zero_copy_only=False)
    starts, text = np.cumsum(n + 1) - (n + 1), np.arange(len(n))
    ids = np.full(len(found) + len(n), end, np.int32)
    ids[np.arange(len(found)) + np.repeat(text, n)] = found
    return ids, starts


def fold() -> F.Column:
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 7


def counted(docs: DataFrame) -> DataFrame:
    """word (bytes), c over docs; the end counts once a document. A slice of texts is counted in Arrow, the rest is Spark's
    aggregation, so that memory is bounded whatever the vocabulary."""
    def run(batches):
        import pyarrow as pa

        for part in (whole.slice(a, b - a) for whole in batches for a, b in together(whole.column("text"), COUNTED)):
            found = words_of(part.column("text"))[0].value_counts()
            pa.default_memory_pool().release_unused()  # workers live on, and the pool would keep what it had
            word, c = found.field("values").cast(pa.binary()), found.field("counts")
            yield pa.RecordBatch.from_arrays([pa.concat_arrays([word, pa.array([b"\n"])]), pa.concat_arrays([c, pa.array([part.num_rows])])], ["word", "c"])

    return docs.select("text").mapInArrow(run, "word binary, c long").groupBy("word").agg(F.sum("c").alias("c"))


class Network:
    """Parameters by name, in one flat float32 vector; ids from `size` on are words outside the vocabulary."""

    def __init__(self, size: int, flat=None):
        import numpy as np

        self.size, self.classes = size, -(-size // CLASS) + 1
        e, h, c = EMBEDDED, STATE, self.classes
        shapes = {"embed": (size + 1, e), "wx": (e, 3 * h), "wh": (h, 3 * h), "b": (3 * h,), "wc": (h, c), "bc": (c,), "wo": (size, h), "bo": (size,)}
        total = sum(math.prod(s) for s in shapes.values())
        self.flat = np.zeros(total, np.float32) if flat is None else np.asarray(flat, np.float32)
        at = 0
        for name, s in shapes.items():
            setattr(self, name, self.flat[at : at + math.prod(s)].reshape(s))
            at += math.prod(s)

    @classmethod
    def initial(cls, counts: list[int], rest: int) -> Network:
        """Random weights, and output biases that give each word its share of the training tokens."""
        import numpy as np

        net = cls(len(counts))
        rng = np.random.default_rng(4)
        for name in ("embed", "wx", "wh", "wc", "wo"):
            p = getattr(net, name)
            p[:] = rng.standard_normal(p.shape) * (0.3 if name == "embed" else 0.5 / math.sqrt(p.shape[0] if name != "wo" else STATE) if name != "wc" else 0.1)
        net.wo *= 0.2
        c = np.array(counts, np.float64) + 1
        mass = np.array([c[k : k + CLASS].sum() for k in range(0, len(c), CLASS)] + [rest + 1.0])
        net.bc[:] = np.log(mass / mass.sum())
        net.bo[:] = np.log(c)
        return net

    def gates(self, rows=slice(None)):
        """What a word adds to each gate, (3 * STATE, words), and the state's weights, (3 * STATE, STATE). They are scaled to
        be exponents: a sigmoid is 1 / (1 + exp(-x)), and the candidates' tanh is 2 / (1 + exp(-2 x)) - 1."""
        import numpy as np

        s = STATE
        table, wh = self.wx.T @ self.embed[rows].T, self.wh.T.copy()
        table += self.b[:, None]
        for x in (table, wh):
            x[: 2 * s] *= np.float32(-1)
            x[2 * s :] *= np.float32(-2)
        return table, wh

    def steps(self, gates, h, inputs, keep, out, tape=None):
        """Runs len(inputs) steps from state h, (STATE, lanes); states after each step go to out, (steps, STATE, lanes). Lanes
        come last, so that each gate is a slice. tape: arrays (steps, .., lanes) for the STATE rows of states before, the
        3 * STATE of gates (the state's part, in the candidates' scale, in the last), and the STATE of candidates."""
        import numpy as np

        table, wh = gates
        s, (length, lanes) = STATE, inputs.shape
        inputs = inputs.astype(np.intp)
        ends = (keep == 0).any(1)
        g, u, n = (np.empty((q * s, lanes), np.float32) for q in (3, 3, 1))
        one, two = np.float32(1), np.float32(2)
        with np.errstate(over="ignore"):  # exp of a closed gate is infinite, and 1 / (1 + it) the 0 that it should be
            for t in range(length):
                if ends[t]:
                    h = h * keep[t].astype(np.float32)
                if tape is not None:
                    tape[0][t], u, n = h, tape[1][t], tape[2][t]
                np.matmul(wh, h, out=u)
                table.take(inputs[t], axis=1, out=g, mode="clip")
                zr = u[: 2 * s]
                zr += g[: 2 * s]
                np.exp(zr, out=zr)
                zr += one
                np.divide(one, zr, out=zr)
                np.multiply(u[2 * s :], zr[s:], out=n)
                n += g[2 * s :]
                np.exp(n, out=n)
                n += one
                np.divide(two, n, out=n)
                n -= one
                o = out[t]
                np.subtract(h, n, out=o)
                o *= zr[:s]
                o += n
                h = o
        return h

    def output(self, states, targets, grads: Network | None = None):
        """Natural log probabilities of targets (ids; `size` is the class of other words); with grads, also
        adds the gradient of their negative sum and returns that of the states. A row of states for each target; they are
        read as columns, so the transpose of (STATE, targets) is the cheap form."""
        import numpy as np

        s, c, m = STATE, self.classes, len(targets)
        kind = np.minimum(targets // CLASS, c - 1).astype(np.int16)
        kind[targets >= self.size] = c - 1
        # Columns lie by class, with a 1 below each state for the biases; a class's words are a slice then.
        order = np.argsort(kind, kind="stable")
        edges = [0, *np.cumsum(np.bincount(kind, minlength=c)).tolist()]
        kind, rows = kind[order], np.arange(m)
        st = np.empty((s + 1, m), np.float32)
        np.take(states.T, order, axis=1, out=st[:s], mode="clip")
        st[s] = 1
        p = np.vstack([self.wc, self.bc]).T @ st  # a row for each class
        found = p[kind, rows]
        if not (p.max(initial=0) < 80 and found.min(initial=0) > -80):  # else exp neither overflows nor loses the target
            p -= p.max(0)
            found = p[kind, rows]
        np.exp(p, out=p)
        total = p.sum(0)
        found -= np.log(total)
        back = None
        if grads is not None:
            p /= total
            p[kind, rows] -= 1
            g = p @ st.T
            grads.wc += g[:, :s].T
            grads.bc += g[:, s]
            back = self.wc @ p
        words = np.zeros(((c - 1) * CLASS, s + 1), np.float32)
        words[: self.size, :s], words[: self.size, s], words[self.size :, s] = self.wo, self.bo, -1e30
        words = words.reshape(c - 1, CLASS, s + 1)
        m = edges[c - 1]
        p, rows, at = np.empty((m, CLASS), np.float32), rows[:m], targets[order[:m]] - kind[:m].astype(np.int64) * CLASS
        own = [(k, a, b) for k, (a, b) in enumerate(zip(edges[: c - 1], edges[1:c])) if a < b]
        for k, a, b in own:
            np.matmul(st[:, a:b].T, words[k].T, out=p[a:b])
        picked = p[rows, at]
        if not (p.max(initial=0) < 80 and picked.min(initial=0) > -80):
            p -= p.max(1, keepdims=True)
            picked = p[rows, at]
        np.exp(p, out=p)
        total = p @ np.ones(CLASS, np.float32)
        found[:m] += picked - np.log(total)
        out = np.empty_like(found)
        out[order] = found
        if grads is None:
            return out, None
        # p - 1 at the targets, times the totals, which the states and what goes back are divided by instead.
        p[rows, at] -= total
        total = 1 / total
        scaled, more, g = st[:, :m] * total, np.empty((s, m), np.float32), np.zeros_like(words)
        for k, a, b in own:
            np.matmul(p[a:b].T, scaled[:, a:b].T, out=g[k])
            np.matmul(words[k, :, :s].T, p[a:b].T, out=more[:, a:b])
        g = g.reshape(-1, s + 1)[: self.size]
        grads.wo += g[:, :s]
        grads.bo += g[:, s]
        more *= total
        back[:, :m] += more
        place = np.empty_like(order)
        place[order] = np.arange(len(order))
        return out, np.take(back, place, axis=1).T


def lanes(docs: list, n: int, end: int, spare: int = 4):
    """Documents (id arrays) dealt to n lanes: inputs, targets, keep (0 at a start) and document of each step."""
    import numpy as np

    # No lane is much longer than the others, unless one document is; then there are fewer (spare 1: about as many as
    # are full until the longest document ends).
    n = max(1, min(n, len(docs), -(-spare * sum(map(len, docs)) // max(1, max(map(len, docs))))))
    sizes = np.fromiter(map(len, docs), np.int64, len(docs))
    length, lane, at = [(0, k) for k in range(n)], np.empty(len(docs), np.int64), np.empty(len(docs), np.int64)
    import heapq

    for i in np.argsort(-sizes, kind="stable").tolist():
        size, k = length[0]
        lane[i], at[i] = k, size
        heapq.heapreplace(length, (size + len(docs[i]), k))
    steps = max(x for x, _ in length)
    inputs = np.full((steps, n), end, np.int16 if VOCABULARY < 32_000 else np.int32)
    targets, owner = inputs.copy(), np.full((steps, n), -1, np.int32)
    keep = np.ones((steps, n), np.int8)
    keep[at, lane] = 0
    for a in range(0, len(docs), 256):  # at once
        own = np.arange(a, min(a + 256, len(docs)))
        flat, size = np.concatenate(docs[a : a + 256]), sizes[own]
        starts = np.cumsum(size) - size
        before = np.r_[end, flat[:-1]]
        before[starts] = end
        place = np.arange(len(flat)) * n + np.repeat((at[own] - starts) * n + lane[own], size)
        inputs.ravel()[place], targets.ravel()[place], owner.ravel()[place] = before, flat, np.repeat(own, size)
    return inputs, targets, keep, owner


def columns(x):
    """(steps, rows, lanes) as (rows, steps * lanes)."""
    return x.transpose(1, 0, 2).reshape(x.shape[1], -1)


def fit_copy(net: Network, docs: list, end: int) -> int:
    """Trains net in place by truncated backpropagation; returns the number of tokens seen."""
    import numpy as np

    m, v, step, seen = np.zeros_like(net.flat), np.zeros_like(net.flat), 0, 0
    s = STATE
    inputs, targets, keep, owner = lanes(docs, TRAIN_LANES, end, 1)
    h, place = np.zeros((s, inputs.shape[1]), np.float32), np.zeros(net.size + 1, np.int64)
    for a in range(0, len(inputs), SPAN):
        x, y, k, live = inputs[a : a + SPAN], targets[a : a + SPAN], keep[a : a + SPAN], owner[a : a + SPAN] >= 0
        on = live.any(0)
        if not on.all():  # lanes that have ended
            inputs, targets, keep, owner, h = inputs[:, on], targets[:, on], keep[:, on], owner[:, on], h[:, on]
            x, y, k, live = x[:, on], y[:, on], k[:, on], live[:, on]
        grads = Network(net.size)
        hp, gate, n, states = (np.empty((len(x), q * s, x.shape[1]), np.float32) for q in (1, 3, 1, 1))
        used = np.flatnonzero(np.bincount(x.ravel(), minlength=net.size + 1))  # only rows of words in the span move
        place[used] = np.arange(len(used))
        x = place[x]
        h = net.steps(net.gates(used), h, x, k, states, (hp, gate, n)).copy()
        on, states, back = np.flatnonzero(live.ravel()), columns(states), np.zeros((s, x.size), np.float32)
        if len(on) == x.size:
            back = net.output(states.T, y.ravel(), grads)[1].T
        else:
            back[:, on] = net.output(states[:, on].T, y.ravel()[on], grads)[1].T
        back = back.reshape(s, *x.shape)
        z, r, un = gate[:, :s], gate[:, s : 2 * s], gate[:, 2 * s :]
        # d: of the state's part of the candidates' sum, of the gates z and r, and of the candidates' sum. It starts as what a
        # state's gradient is multiplied with; un is in the scale of an exponent, -2 times the state's part.
        d = np.empty((len(x), 4, s, x.shape[1]), np.float32)
        to_u, to_z, to_r, to_n = (d[:, q] for q in range(4))
        np.multiply(n, n, out=to_n)
        np.subtract(1, to_n, out=to_n)
        part = 1 - z
        to_n *= part
        np.subtract(hp, n, out=to_z)
        part *= z
        to_z *= part
        np.multiply(to_n, r, out=to_u)
        np.subtract(1, r, out=part)
        part *= un
        part *= np.float32(-0.5)
        np.multiply(to_u, part, out=to_r)
        dh, flat, ends = np.zeros((s, x.shape[1]), np.float32), d.reshape(len(x), 4 * s, -1), (k == 0).any(1)
        turned = np.concatenate([net.wh[:, 2 * s :], net.wh[:, : 2 * s]], axis=1)
        for t in range(len(x) - 1, -1, -1):
            dh += back[:, t]
            q = d[t]
            q *= dh
            dh *= z[t]
            dh += turned @ flat[t, : 3 * s]
            if ends[t]:
                dh *= k[t].astype(np.float32)
        x, d = x.ravel(), columns(flat)
        # left: all that the gates' weights are multiplied with, the states before, the words' rows and a 1.
        left = np.empty((s + EMBEDDED + 1, len(x)), np.float32)
        left[:s], left[-1] = columns(hp), 1
        np.take(net.embed[used].T, x, axis=1, out=left[s:-1], mode="clip")
        g = left[:s] @ d[: 3 * s].T
        grads.wh[:, : 2 * s] += g[:, s:]
        grads.wh[:, 2 * s :] += g[:, :s]
        g = left[s:] @ d[s:].T
        grads.wx += g[:-1]
        grads.b += g[-1]
        order = np.argsort(x.astype(np.int16), kind="stable")
        starts = np.r_[0, np.cumsum(np.bincount(x, minlength=len(used)))[:-1]]
        grads.embed[used] += np.add.reduceat((d[s:].T @ net.wx.T)[order], starts, axis=0)
        g = grads.flat / max(1, len(on))
        norm = float(np.sqrt(g @ g))
        if norm > 1:
            g /= norm
        step += 1
        seen += len(on)
        g *= 0.1
        m *= 0.9
        m += g
        g *= g
        v *= 0.99
        v += g  # (0.1 g)**2 is 0.01 g**2
        np.sqrt(v / (1 - 0.99**step), out=g)
        g += 1e-6
        np.divide(m, g, out=g)
        g *= RATE / (1 - 0.9**step)
        net.flat -= g
    return seen


def log_probabilities(net: Network, docs: list, end: int):
    """Natural log probability of each document, its words outside the vocabulary by their class only."""
    import numpy as np

    out = np.zeros(len(docs))
    if not docs:
        return out
    inputs, targets, keep, owner = lanes(docs, LANES, end)
    gates, h = net.gates(), np.zeros((STATE, inputs.shape[1]), np.float32)
    a = 0
    while a < len(inputs):
        # Lanes end at different steps; the rest goes on with those that have a document still.
        live = np.flatnonzero(owner[a] >= 0)
        if len(live) < 0.7 * inputs.shape[1]:
            inputs, targets, keep, owner, h = inputs[:, live], targets[:, live], keep[:, live], owner[:, live], h[:, live]
        x, y, own = inputs[a : a + WINDOW], targets[a : a + WINDOW].ravel(), owner[a : a + WINDOW].ravel()
        states = np.empty((len(x), STATE, x.shape[1]), np.float32)
        h = net.steps(gates, h, x, keep[a : a + WINDOW], states)
        states, on = columns(states), np.flatnonzero(own >= 0)
        if len(on) < len(own):
            states, y, own = states[:, on], y[on], own[on]
        got, _ = net.output(states.T, y)
        out += np.bincount(own, got, minlength=len(docs))
        a += WINDOW
    return out


def averaged(copies: DataFrame, shards: int) -> tuple[int, object] | None:
    """Tokens, and the mean weighted by tokens, of copies (shard, n, flat): sums in a tree, each in the order of its shards."""
    def add(pdf):
        import numpy as np
        import pandas as pd

        pdf = pdf.sort_values("shard")
        total = np.zeros(len(pdf["flat"].iloc[0]))
        for x in pdf["flat"]:
            total += np.asarray(x, np.float64)
        return pd.DataFrame({"shard": [int(pdf["shard"].iloc[0]) // FAN], "n": [int(pdf["n"].sum())], "flat": [total]})

    while True:
        copies = copies.groupBy(F.floor(F.col("shard") / FAN)).applyInPandas(add, "shard long, n long, flat array<double>")
        shards = -(-shards // FAN)
        if shards <= 1:
            break
    got = copies.collect()  # one row
    return (got[0]["n"], got[0]["flat"]) if got else None


def trainer(shared):
    """A function that trains a copy of the shared network on one shard."""
    def run(shard):
        import numpy as np
        import pyarrow as pa
        import pyarrow.compute as pc

        size, flat, ids = shared.value
        order, end = pc.sort_indices(shard, [(x, "ascending") for x in ("h", "doc_id", "text")]), ids[b"\n"]
        known, docs = pa.array(sorted(ids, key=ids.get), pa.binary()), []
        for a in range(0, len(order), 512):  # texts at once
            found, starts = numbers_of(*words_of(shard.column("text").take(order.slice(a, 512)).combine_chunks()), known, size, end)
            docs += np.split(found, starts[1:])
        pa.default_memory_pool().release_unused()
        own = Network(size, flat.copy())
        seen = fit_copy(own, docs, end)
        return pa.table({"shard": shard.column("shard").slice(0, 1), "n": pa.array([seen], pa.int64()), "flat": pa.array([own.flat * np.float64(seen)], pa.list_(pa.float64()))})

    return run


def trained(docs: DataFrame, net: Network, ids: dict) -> Network:
    """net after ROUNDS rounds of copies trained on shards and averaged. docs: doc_id, text."""
    import numpy as np

    sc = docs.sparkSession.sparkContext
    turn = F.pmod(F.xxhash64("doc_id"), F.lit(ROUNDS))
    size_of = {r["turn"]: r["size"] for r in docs.groupBy(turn.alias("turn")).agg(F.sum(F.octet_length(F.coalesce("text", F.lit("")))).alias("size")).collect()}  # ROUNDS rows
    for k in range(ROUNDS):
        shards = max(1, -(-size_of.get(k, 0) // SHARD))
        shared = sc.broadcast((net.size, net.flat.copy(), ids))  # of a fixed size: VOCABULARY words

        h = F.xxhash64(F.lit(2), "doc_id", "text")
        part = docs.where(turn == k).select("doc_id", F.coalesce("text", F.lit("")).alias("text"), h.alias("h"), F.pmod(h, F.lit(shards)).alias("shard"))
        # By a number of its own, so that shards are not put together in a task for being small.
        part = part.repartition(min(shards, TASKS), "shard")
        got = averaged(part.groupBy("shard").applyInArrow(trainer(shared), "shard long, n long, flat array<double>"), shards)
        if got and got[0]:
            net = Network(net.size, np.asarray(got[1]) / got[0])
        shared.unpersist()
    return net


def together(column, most: int = TOGETHER):
    """Stretches of a column of texts of about `most` bytes; a text is never cut."""
    at, size = 0, 0
    for k in range(len(column)):
        size += column[k].as_buffer().size if column[k].is_valid else 1
        if size >= most or k + 1 == len(column):
            yield at, k + 1
            at, size = k + 1, 0


def scores(docs: DataFrame, training: DataFrame) -> DataFrame:
    """doc_id, n_tokens, n_known, train_tokens, base_score, score of every row of docs (doc_id, text)."""
    counts = common.staged(counted(training), "counts")
    n, v = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.lit(1))).first()
    # Bands of counts, at most some 1500: the head is all words of the highest bands that hold HEAD words at most.
    band = F.floor(F.log("c") * 50)
    bands = sorted(((r["band"], r["count"]) for r in counts.groupBy(band.alias("band")).count().collect()), reverse=True)
    least, words = None, 0
    for b, size in bands:
        if words + size > HEAD:
            break
        least, words = b, words + size
    in_head = (band >= least) if least is not None else F.lit(False)
    head = {bytes(r["word"]): r["c"] for r in counts.where(in_head).collect()}  # at most HEAD rows
    named = sorted((w for w in head if w != b"\n"), key=lambda w: (-head[w], w))[: VOCABULARY - 1]
    named = sorted([*named, b"\n"], key=lambda w: (-head.get(w, 0), w))
    ids = {w: i for i, w in enumerate(named)}
    inside = [head.get(w, 0) for w in named]
    rest, rest_words = n - sum(inside), v - sum(1 for w in named if w in head)
    net = trained(training, Network.initial(inside, rest), ids)

    rows = common.numbered(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"))
    inner = set(named)
    ordered = [*named, *(w for w in head if w not in inner)]
    shared = docs.sparkSession.sparkContext.broadcast((net.size, net.flat, ordered, np.array([head.get(w, 0) for w in ordered], np.int64)))  # HEAD words at most

    def run(batches):
        import numpy as np
        import pyarrow as pa

        size, flat, ordered, counted = shared.value
        net = Network(size, flat)
        place = pa.array(ordered, pa.binary())  # the model's words come first
        logs = np.log10(np.r_[counted, 0].astype(float) + 1)  # the last, at -1, is of words that are not here
        met, end = np.r_[counted > 0, False], ordered.index(b"\n")
        for batch in (whole.slice(a, b - a) for whole in batches for a, b in together(whole.column("text"))):
            words, n = words_of(batch.column("text"))
            at, starts = numbers_of(words, n, place, -1, end)
            pa.default_memory_pool().release_unused()
            text = np.repeat(np.arange(len(n)), n + 1)
            inner = np.where((at >= 0) & (at < size), at, size)
            value = log_probabilities(net, np.split(inner, starts[1:]), end) / math.log(10)
            base, outside = logs[at], inner == size
            # Words that are not in the head, each once a text with its times there.
            far = np.flatnonzero(at < 0)
            rare = words.take(pa.array(far - text[far])).dictionary_encode()
            pair, times = np.unique(text[far] * max(1, len(rare.dictionary)) + rare.indices.to_numpy(zero_copy_only=False), return_counts=True)
            edges = pa.array(np.searchsorted(pair, np.arange(len(n) + 1) * max(1, len(rare.dictionary))), pa.int32())
            rare = rare.dictionary.take(pa.array(pair % max(1, len(rare.dictionary)))).cast(pa.binary())
            columns = [(n + 1, pa.int64()), (np.add.reduceat(met[at].astype(np.int64), starts), pa.int64()), (np.add.reduceat(base, starts), pa.float64()), (np.add.reduceat(base * outside, starts), pa.float64()), (np.add.reduceat(outside.astype(np.int64), starts), pa.int64()), (value, pa.float64())]
            lists = [pa.ListArray.from_arrays(edges, rare), pa.ListArray.from_arrays(edges, pa.array(times, pa.int64()))]
            yield pa.RecordBatch.from_arrays([batch.column("row_id"), batch.column("doc_id"), *(pa.array(x, t) for x, t in columns), *lists], ["row_id", "doc_id", "n_tokens", "known", "base", "tail", "other", "inner", "rare", "times"])

    seen = common.staged(rows.mapInArrow(run, "row_id long, doc_id long, n_tokens long, known long, base double, tail double, other long, inner double, rare array<binary>, times array<long>"), "scored")
    far = seen.select("row_id", F.explode(F.arrays_zip("rare", "times")).alias("x")).select("row_id", F.col("x.rare").alias("word"), F.col("x.times").alias("times"))
    met = far.join(counts.where(~in_head), "word").groupBy("row_id").agg(F.sum("times").alias("more"), F.sum(F.col("times") * F.log10(F.col("c") + 1)).alias("logs"))
    out = seen.drop("rare", "times").join(met, "row_id", "left")
    logs = F.coalesce("logs", F.lit(0.0))
    return out.select(
        "doc_id",
        "n_tokens",
        (F.col("known") + F.coalesce("more", F.lit(0))).alias("n_known"),
        F.lit(n).cast("long").alias("train_tokens"),
        (F.col("base") + logs - F.col("n_tokens") * F.lit(math.log10(n + v + 1))).alias("base_score"),
        (F.col("inner") + F.col("tail") + logs - F.col("other") * F.lit(math.log10(rest + rest_words + 1))).alias("score"),
    )


def query(docs: DataFrame) -> DataFrame:
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    # A null id has no remainder; it is not trained on, and held out.
    out = scores(docs, docs.where(F.coalesce(fold() != 2, F.lit(False))))
    return out.select("doc_id", F.coalesce(fold() == 2, F.lit(True)).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")
