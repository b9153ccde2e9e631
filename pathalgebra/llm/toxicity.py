"""Toxicity by a bidirectional gated recurrent network with attention pooling.

A text's words are read in windows that overlap by half.  A word enters as a
vector of two parts: an embedding of the word itself and the mean embedding of
its character n-grams, each with a weight of evidence, so that new forms of a
known stem are seen too.  Two gated recurrent layers read a window from either
end; attention pools their states; the text's score is that of its worst window.

Everything is numpy: training runs in one task over a bounded sample of
labelled rows and picks each text's worst window anew in every round.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathalgebra.llm.fitting import LONGEST, MOST_CHARS, chosen_keys, fit_in_task
from pathalgebra.llm.langid import held_out
from pathalgebra.llm.memory import lean
from pathalgebra.llm.word_features import affixes, letter_matrix, letter_table, ngrams, whole
from pathalgebra.llm.words import blocks, ragged, split_words

WINDOW, STRIDE = 32, 16
_WORD_BITS, _GRAM_BITS = 14, 15


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


def word_parts(words: list[str]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(which words, word number, n-gram numbers, which n-grams exist)."""
    for which, points, lengths in letter_matrix(words):
        values, there = [], []
        for n in (3, 4, 5):
            v, e = ngrams(points, lengths, n)
            values.append(v)
            there.append(e)
        for n in (5, 6):
            v, _ = affixes(points, lengths, n)
            values.append(v[:, None])
            there.append((lengths >= n)[:, None])
        yield which, whole(points), np.concatenate(values, axis=1), np.concatenate(there, axis=1)


class Network:
    """Weights and both passes; ``hidden`` states for each direction."""

    def __init__(self, hidden: int = 8, word_dim: int = 6, gram_dim: int = 6, seed: int = 3):
        rng = np.random.default_rng(seed)

        def draw(*shape: int, scale: float) -> np.ndarray:
            return (rng.normal(size=shape) * scale).astype(np.float32)

        self.hidden, width = hidden, word_dim + gram_dim + 2
        self.w = {
            "words": draw(1 << _WORD_BITS, word_dim, scale=0.1), "grams": draw(1 << _GRAM_BITS, gram_dim, scale=0.1),
            "out": draw(2 * hidden, scale=0.3), "bias": np.zeros(1, np.float32), "att": draw(2 * hidden, hidden, scale=0.3), "pick": draw(hidden, scale=0.3),
        }
        for side in "fb":
            self.w |= {f"in_{side}": draw(width, 3 * hidden, scale=0.3), f"add_{side}": np.zeros(3 * hidden, np.float32), f"gates_{side}": draw(hidden, 2 * hidden, scale=0.3), f"state_{side}": draw(hidden, hidden, scale=0.3)}
        self.word_evidence = np.zeros(1 << _WORD_BITS, np.float32)
        self.gram_evidence = np.zeros(1 << _GRAM_BITS, np.float32)

    def inputs(self, words: list[str], trace: list | None = None) -> np.ndarray:
        """The vector of each distinct word."""
        w = self.w
        a, b = w["words"].shape[1], w["grams"].shape[1]
        out = np.zeros((len(words), a + b + 2), np.float32)
        for which, name, grams, there in word_parts(words):
            name = (name >> np.uint64(64 - _WORD_BITS)).astype(np.int64)
            grams = (grams >> np.uint64(64 - _GRAM_BITS)).astype(np.int64)
            count = np.maximum(there.sum(axis=1), 1)[:, None].astype(np.float32)
            total = np.zeros((len(which), b), np.float32)
            strongest = np.zeros(len(which), np.float32)
            for k in range(grams.shape[1]):
                real = there[:, k]
                total += w["grams"][grams[:, k]] * real[:, None]
                np.maximum(strongest, np.where(real, self.gram_evidence[grams[:, k]], 0), out=strongest)
            out[which, :a] = w["words"][name]
            out[which, a : a + b] = total / count
            out[which, a + b] = self.word_evidence[name]
            out[which, a + b + 1] = strongest
            if trace is not None:
                trace.append((which, name, grams, there, count))
        return out

    def _read(self, side: str, gates: np.ndarray, at: np.ndarray, lengths: np.ndarray, keep: list | None) -> np.ndarray:
        """States of all windows after each place; ``at``: places x windows, into ``gates``."""
        w, h = self.w, self.hidden
        places, n = at.shape
        states = np.zeros((places, n, h), np.float32)
        now = np.zeros((n, h), np.float32)
        u, v = w[f"gates_{side}"], w[f"state_{side}"]
        for t in range(places) if side == "f" else range(places - 1, -1, -1):
            x = gates[at[t]]
            zr = sigmoid(x[:, : 2 * h] + now @ u)
            z, r = zr[:, :h], zr[:, h:]
            held = r * now
            c = np.tanh(x[:, 2 * h :] + held @ v)
            new = now + z * (c - now)
            beyond = lengths <= t
            if beyond.any():
                new[beyond] = now[beyond]
            if keep is not None:
                keep.append((t, now, z, r, held, c, beyond))
            states[t] = now = new
        return states

    def forward(self, vectors: np.ndarray, at: np.ndarray, lengths: np.ndarray, trace: dict | None = None) -> np.ndarray:
        """Log-odds of each window; ``at``: places x windows, into ``vectors``."""
        w = self.w
        keep_f, keep_b = ([], []) if trace is not None else (None, None)
        f = self._read("f", vectors @ w["in_f"] + w["add_f"], at, lengths, keep_f)
        b = self._read("b", vectors @ w["in_b"] + w["add_b"], at, lengths, keep_b)
        both = np.concatenate([f, b], axis=2)
        inner = np.tanh(both @ w["att"])
        score = inner @ w["pick"]
        real = np.arange(at.shape[0])[:, None] < lengths[None, :]
        score = np.where(real, score, -1e9)
        share = np.exp(score - score.max(axis=0, initial=-1e9)) * real
        share /= np.maximum(share.sum(axis=0), 1e-9)
        pooled = (share[:, :, None] * both).sum(axis=0)
        if trace is not None:
            trace |= {"both": both, "inner": inner, "share": share, "pooled": pooled, "f": keep_f, "b": keep_b}
        return pooled @ w["out"] + w["bias"][0]

    def gradients(self, vectors: np.ndarray, at: np.ndarray, lengths: np.ndarray, wrong: np.ndarray, trace: dict) -> tuple[dict, np.ndarray]:
        """Gradients of sum(wrong * log-odds) by weights and by ``vectors``."""
        w, h, g = self.w, self.hidden, {}
        both, inner, share, pooled = trace["both"], trace["inner"], trace["share"], trace["pooled"]
        g["out"], g["bias"] = pooled.T @ wrong, np.array([wrong.sum()], np.float32)
        d_pooled = wrong[:, None] * w["out"]
        d_share = (both * d_pooled).sum(axis=2)
        d_both = share[:, :, None] * d_pooled
        d_score = share * (d_share - (share * d_share).sum(axis=0))
        d_pre = d_score[:, :, None] * w["pick"] * (1 - inner * inner)
        g["pick"] = (inner * d_score[:, :, None]).sum(axis=(0, 1))
        g["att"] = both.reshape(-1, 2 * h).T @ d_pre.reshape(-1, h)
        d_both = d_both + d_pre @ w["att"].T
        d_vectors = np.zeros_like(vectors)
        for side, d_states in (("f", d_both[:, :, :h]), ("b", d_both[:, :, h:])):
            u, v = w[f"gates_{side}"], w[f"state_{side}"]
            g_u, g_v = np.zeros_like(u), np.zeros_like(v)
            d_gates = np.zeros((len(vectors), 3 * h), np.float32)
            back = np.zeros((at.shape[1], h), np.float32)
            for t, now, z, r, held, c, beyond in reversed(trace[side]):
                d_new = back + d_states[t]
                live = ~beyond[:, None]
                d_c = d_new * z * (1 - c * c) * live
                d_z = d_new * (c - now) * z * (1 - z) * live
                d_held = d_c @ v.T
                d_r = d_held * now * r * (1 - r)
                d_zr = np.concatenate([d_z, d_r], axis=1)
                back = np.where(live, d_new * (1 - z) + d_held * r + d_zr @ u.T, d_new)
                g_u += now.T @ d_zr
                g_v += held.T @ d_c
                np.add.at(d_gates, at[t], np.concatenate([d_zr, d_c], axis=1))
            g[f"gates_{side}"], g[f"state_{side}"] = g_u, g_v
            g[f"in_{side}"], g[f"add_{side}"] = vectors.T @ d_gates, d_gates.sum(axis=0)
            d_vectors += d_gates @ w[f"in_{side}"].T
        return g, d_vectors


def cut_windows(sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, first word, words) of all windows; an empty text has one empty window."""
    count = np.maximum(1, -(-(sizes - (WINDOW - STRIDE)) // STRIDE))
    text = np.repeat(np.arange(len(sizes)), count)
    number = np.arange(len(text)) - np.repeat(np.cumsum(count) - count, count)
    return text, number * STRIDE, np.minimum(WINDOW, sizes[text] - number * STRIDE)


def window_scores(net: Network, codes: np.ndarray, begins: np.ndarray, sizes: np.ndarray, vectors: np.ndarray, step: int = 2048) -> tuple[np.ndarray, ...]:
    """(text, first word, words, log-odds) of all windows of a block."""
    text, first, words = cut_windows(sizes)
    odds = np.empty(len(text), np.float32)
    padded = np.concatenate([codes, np.zeros(WINDOW, codes.dtype)])
    for at in range(0, len(text), step):
        part = slice(at, at + step)
        places = begins[text[part]] + first[part] + np.arange(WINDOW)[:, None]
        odds[part] = net.forward(vectors, padded[np.minimum(places, len(padded) - 1)], words[part])
    return text, first, words, odds


def evidence(codes: np.ndarray, sizes: np.ndarray, words: list[str], toxic: np.ndarray, net: Network, least: int = 5) -> None:
    """Smoothed log-odds of words and n-grams by labelled texts; rare ones have none."""
    yes, no = toxic.sum() + 1.0, (1 - toxic).sum() + 1.0
    begins = np.cumsum(sizes) - sizes
    for bits, table, whole_word in ((_WORD_BITS, net.word_evidence, True), (_GRAM_BITS, net.gram_evidence, False)):
        shift = np.uint64(64 - bits)
        count = np.zeros(len(words), np.int64)
        parts = []
        for which, name, grams, there in word_parts(words):
            count[which] = 1 if whole_word else there.sum(axis=1)
            parts.append((which, ((name if whole_word else grams[there]) >> shift).astype(np.int32)))
        first = np.cumsum(count) - count
        flat = np.zeros(int(count.sum()), np.int32)
        for which, cells in parts:
            flat[ragged(first[which], count[which])] = cells
        del parts
        pos, neg = np.zeros(1 << bits), np.zeros(1 << bits)
        for k in range(len(sizes)):  # a text at a time keeps memory small
            own = np.unique(codes[begins[k] : begins[k] + sizes[k]])
            cells = np.unique(flat[ragged(first[own], count[own])])
            (pos if toxic[k] else neg)[cells] += 1
        odds = np.log((pos + 0.1) / yes) - np.log((neg + 0.1) / no)
        table[:] = np.where(pos >= least, np.clip(odds, 0, 5) * pos / (pos + least), 0)


def train_network(texts: list[str], labels: list[int], rounds: int = 6, seed: int = 3, batch: int = 256, rate: float = 0.01) -> Network:
    """Worst windows of toxic texts against worst and random windows of the others."""
    net = Network(seed=seed)
    if not texts:
        return net
    ends, codes, words = split_words(pa.array(texts, pa.string()), letter_table())
    sizes = np.diff(np.concatenate([[0], ends]))
    begins = ends - sizes
    toxic = np.array(labels, np.float64)
    evidence(codes, sizes, words, toxic, net)
    w = net.w
    w["bias"][0] = np.log((toxic.sum() + 0.5) / (len(toxic) - toxic.sum() + 0.5))
    first_m, second_m = {k: np.zeros_like(v) for k, v in w.items()}, {k: np.zeros_like(v) for k, v in w.items()}
    rng, t = np.random.default_rng(seed), 0
    padded = np.concatenate([codes, np.zeros(WINDOW, codes.dtype)])
    for round_ in range(rounds):
        text, first, count, odds = window_scores(net, codes, begins, sizes, net.inputs(words))
        if round_ == 0:  # nothing is learned yet: the window with most evidence
            strength = np.concatenate([[0], np.cumsum(net.inputs(words)[codes, -1])]) if len(codes) else np.zeros(1)
            odds = strength[np.minimum(begins[text] + first + np.maximum(count, 0), len(strength) - 1)] - strength[np.minimum(begins[text] + first, len(strength) - 1)]
        order = np.lexsort((odds, text))
        last = np.append(np.flatnonzero(np.diff(text[order])), len(order) - 1)
        worst = order[last]
        any_window = rng.permutation(np.flatnonzero(toxic[text] == 0))[: len(worst)]
        chosen = rng.permutation(np.concatenate([worst, any_window]))
        for at in range(0, len(chosen), batch):
            part = chosen[at : at + batch]
            places = padded[np.minimum(begins[text[part]] + first[part] + np.arange(WINDOW)[:, None], len(padded) - 1)]
            local, back = np.unique(places, return_inverse=True)
            back = back.reshape(places.shape)
            steps: list = []
            vectors = net.inputs([words[i] for i in local] if words else [""] * len(local), steps)
            trace: dict = {}
            got = net.forward(vectors, back, count[part], trace)
            wrong = ((sigmoid(got) - toxic[text[part]]) / len(part)).astype(np.float32)
            g, d_vectors = net.gradients(vectors, back, count[part], wrong, trace)
            a, b = w["words"].shape[1], w["grams"].shape[1]
            g["words"], g["grams"] = np.zeros_like(w["words"]), np.zeros_like(w["grams"])
            for which, name, grams, there, n in steps:
                np.add.at(g["words"], name, d_vectors[which, :a])
                spread = d_vectors[which, a : a + b] / n
                rows, cols = np.nonzero(there)
                np.add.at(g["grams"], grams[rows, cols], spread[rows])
            t += 1
            for k, p in w.items():
                grad = g[k] + 1e-5 * p
                first_m[k] += 0.1 * (grad - first_m[k])
                second_m[k] += 0.01 * (grad * grad - second_m[k])
                p -= (rate * (first_m[k] / (1 - 0.9**t)) / (np.sqrt(second_m[k] / (1 - 0.99**t)) + 1e-7)).astype(np.float32)
    return net


def score_block(net: Network, texts: pa.Array) -> np.ndarray:
    """Each text's probability: that of its worst window."""
    ends, codes, words = split_words(texts, letter_table())
    sizes = np.diff(np.concatenate([[0], ends]))
    vectors = net.inputs(words or [""])
    text, _, _, odds = window_scores(net, codes, ends - sizes, sizes, vectors)
    most = np.full(len(sizes), -np.inf)
    np.maximum.at(most, text, odds)
    return sigmoid(most)


def _train_rows(rows: list[tuple]) -> Network:
    by_text = sorted({text: int(toxic > 0) for _, text, toxic in rows}.items())
    return train_network([x for x, _ in by_text], [y for _, y in by_text])


def fit_toxicity(documents: DataFrame, labels: DataFrame, sample: int = 4000, longest: int = LONGEST, most_chars: int = MOST_CHARS) -> Network:
    """A network learned on ``sample`` labelled documents at most.

    Rows whose crc32 of doc_id is a multiple of 5 are held out.  A document with
    several labels counts as toxic if one of them says so.  Texts of more than
    ``longest`` characters aren't learned from, and no more than ``most_chars``
    characters are.
    """
    known = labels.select(F.col("doc_id").alias("chosen"), "toxic").where(F.col("toxic").isNotNull() & F.col("chosen").isNotNull() & ~held_out(F.col("chosen"), 5, 0))
    known = known.groupBy("chosen").agg(F.max("toxic").alias("toxic"))
    known = known.join(F.broadcast(chosen_keys(known, "chosen", sample)), "chosen")
    texts = documents.select("doc_id", "text").where(F.col("text").isNotNull() & (F.length("text") <= longest))
    # At most ``sample`` labels, so the broadcast doesn't grow with the documents.
    rows = texts.join(F.broadcast(known), F.col("doc_id") == F.col("chosen")).select("doc_id", "text", "toxic")
    return fit_in_task(rows, _train_rows, most_chars)


def toxicity_scores(documents: DataFrame, net: Network, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The kept columns and score for every whole text; null counts as empty."""

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(batch.schema.get_field_index("text"))
            found = [score_block(net, block) for _, block in blocks(texts, 3_000_000)]
            rest = [batch.column(batch.schema.get_field_index(c)) for c in keep]
            yield pa.RecordBatch.from_arrays([*rest, pa.array(np.concatenate([np.empty(0), *found]), pa.float64())], names=[*keep, "score"])

    rows = documents.select(*dict.fromkeys([*keep, "text"]))
    kept = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema if f.name in keep)
    return rows.mapInArrow(lean(score), f"{kept}, score double")


def score_toxicity(documents: DataFrame, labels: DataFrame, sample: int = 4000) -> DataFrame:
    """Per document: doc_id, held_out, score, predicted.

    Texts without a word are scored as an empty window.  Without labels the
    network stays as it was drawn.  No rows give no rows.
    """
    scores = toxicity_scores(documents, fit_toxicity(documents, labels, sample))
    return scores.select("doc_id", held_out(F.col("doc_id"), 5, 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
