"""Language of every word of a text by a linear-chain conditional random field.

Words are runs of letters.  A word's score for a language sums weights of its
affixes, its character n-grams and its entry in a lexicon; learned transitions
tie neighbours together, so a switch of language inside a text costs something
and a run of foreign words pays for it.  Forward-backward gives every word's
probabilities; a text's language is the one with the largest expected share.

Forward-backward runs over a block of texts at once.  The block's words form one
long chain that starts anew at each text; it is cut into equal stretches whose
transfer matrices are worked out side by side and then linked in order, which
gives the same numbers as walking through each text.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathalgebra.llm.fitting import LONGEST, MOST_CHARS, chosen_keys, fit_in_task
from pathalgebra.llm.memory import lean
from pathalgebra.llm.word_features import affixes, letter_matrix, letter_table, ngrams, whole
from pathalgebra.llm.words import blocks, split_words

_BITS = 16
_STRETCH = 128
#: Bytes of texts that are labelled together; a word of them takes about a kilobyte meanwhile.
BLOCK = 1_000_000


@dataclass
class Chain:
    """Weights of the field; all arrays are in log space."""

    languages: list[str]
    weights: np.ndarray
    lexicon: np.ndarray
    lexicon_weights: np.ndarray
    start: np.ndarray
    moves: np.ndarray

    def emissions(self, words: list[str]) -> np.ndarray:
        out = np.zeros((len(words), len(self.languages)), np.float32)
        for which, cells, exists, entry in word_cells(words, self.lexicon):
            got = np.zeros((len(which), out.shape[1]), np.float32)
            for k in range(cells.shape[1]):
                got += self.weights[cells[:, k]] * exists[:, k, None]
            known = entry >= 0
            got[known] += self.lexicon_weights[entry[known]]
            out[which] = got
        return out


def word_cells(words: list[str], lexicon: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(which, cells, exists, lexicon entry or -1) of distinct words."""
    shift = np.uint64(64 - _BITS)
    for which, points, lengths in letter_matrix(words):
        cells, exists = [], []
        for n in (2, 3):
            value, there = ngrams(points, lengths, n)
            cells.append(value >> shift)
            exists.append(there)
        for n in (3, 4):
            for value in affixes(points, lengths, n):
                cells.append((value >> shift)[:, None])
                exists.append((lengths >= n)[:, None])
        name = whole(points)
        entry = np.searchsorted(lexicon, name)
        entry = np.where((entry < len(lexicon)) & (lexicon[np.minimum(entry, len(lexicon) - 1)] == name), entry, -1) if len(lexicon) else np.full(len(which), -1)
        yield which, np.concatenate(cells, axis=1).astype(np.int64), np.concatenate(exists, axis=1).astype(np.float32), entry


def forward_backward(scores: np.ndarray, starts: np.ndarray, start: np.ndarray, moves: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Marginals of each place, and expected moves summed over all places.

    ``scores``: log scores (places x labels); ``starts``: True where a text begins.
    """
    n, k = scores.shape
    if not n:
        return np.zeros((0, k)), np.zeros((k, k))
    length = _STRETCH
    count = -(-n // length)
    padded = count * length
    e = np.ones((padded, k))
    e[:n] = np.exp(scores - scores.max(axis=1, keepdims=True))
    fresh = np.zeros(padded, bool)
    fresh[:n] = starts
    fresh[0] = True
    fresh[n:] = True  # what fills the last stretch says nothing about the places before it
    e = np.ascontiguousarray(e.reshape(count, length, k).transpose(1, 0, 2))
    fresh = np.ascontiguousarray(fresh.reshape(count, length).T)
    a, s = np.exp(moves), np.exp(start)
    # Transfer matrices of all stretches, one place at a time.
    whole_move = np.broadcast_to(np.eye(k), (count, k, k)).copy()
    for t in range(length):
        step = whole_move.reshape(-1, k) @ a
        step = step.reshape(count, k, k)
        f = fresh[t]
        if f.any():
            step[f] = whole_move[f].sum(axis=2, keepdims=True) * s
        step *= e[t][:, None, :]
        step /= step.sum(axis=(1, 2), keepdims=True)
        whole_move = step
    into = np.empty((count, k))
    now = np.full(k, 1.0 / k)
    for c in range(count):
        into[c] = now
        now = now @ whole_move[c]
        now /= now.sum()
    out_of = np.empty((count, k))
    now = np.full(k, 1.0)
    for c in range(count - 1, -1, -1):
        out_of[c] = now
        now = whole_move[c] @ now
        now /= now.sum()
    before = np.empty((length, count, k))
    ahead = np.empty((length, count, k))
    now = into
    for t in range(length):
        before[t] = now
        now = now @ a
        f = fresh[t]
        if f.any():
            now[f] = s
        now = now * e[t]
        now /= now.sum(axis=1, keepdims=True)
        ahead[t] = now
    behind = np.empty((length, count, k))
    now = out_of
    for t in range(length - 1, -1, -1):
        behind[t] = now
        seen = now * e[t]
        now = seen @ a.T
        f = fresh[t]
        if f.any():
            now[f] = (seen[f] @ s)[:, None]
        now /= now.sum(axis=1, keepdims=True)
    joint = ahead * behind
    joint /= joint.sum(axis=2, keepdims=True)
    marginals = joint.transpose(1, 0, 2).reshape(padded, k)[:n]
    # A move happens at every place that doesn't begin a text.
    inner = ~fresh
    left, right = before[inner], (e * behind)[inner]
    scale = ((left @ a) * right).sum(axis=1, keepdims=True)
    expected = a * ((left / scale).T @ right)
    return marginals, expected


def train_chain(texts: list[str], labels: list[str], rounds: int = 6, step_words: int = 30_000, seed: int = 5) -> Chain | None:
    """Maximum likelihood by Adam on labelled texts; every word takes its text's label."""
    languages = sorted(set(labels))
    if not languages:
        return None
    index = {x: i for i, x in enumerate(languages)}
    ends, codes, distinct = split_words(pa.array(texts, pa.string()), letter_table())
    gold_text = np.array([index[x] for x in labels])
    sizes = np.diff(np.concatenate([[0], ends]))
    gold = np.repeat(gold_text, sizes)
    k = len(languages)
    # Lexicon: words seen at least three times, nearly always in one language.
    seen = np.zeros((len(distinct), k))
    np.add.at(seen, (codes, gold), 1)
    names = np.zeros(len(distinct), np.uint64)
    for which, points, _ in letter_matrix(distinct):
        names[which] = whole(points)
    listed = np.unique(names[(seen.sum(axis=1) >= 3) & (seen.max(axis=1) >= 0.9 * seen.sum(axis=1))])
    chain = Chain(languages, np.zeros((1 << _BITS, k), np.float32), listed, np.zeros((len(listed), k), np.float32), np.zeros(k), np.zeros((k, k)))
    cells_of: list = [None] * len(distinct)
    for which, cells, exists, entry in word_cells(distinct, listed):
        for row, i in enumerate(which.tolist()):
            cells_of[i] = (cells[row][exists[row] > 0], entry[row])
    parts = [chain.weights, chain.lexicon_weights, chain.start, chain.moves]
    first = [np.zeros_like(p) for p in parts]
    second = [np.zeros_like(p) for p in parts]
    rng, t = np.random.default_rng(seed), 0
    begins = np.concatenate([[0], ends[:-1]])
    for _ in range(rounds):
        order = rng.permutation(len(texts))
        total = np.cumsum(sizes[order])
        cuts = np.searchsorted(total, np.arange(step_words, (total[-1] if len(total) else 0) + step_words, step_words))
        at = 0
        for cut in cuts:
            chosen = order[at : cut + 1]
            at = cut + 1
            chosen = chosen[sizes[chosen] > 0]
            if not len(chosen):
                continue
            places = np.concatenate([np.arange(begins[i], ends[i]) for i in chosen])
            starts = np.zeros(len(places), bool)
            starts[np.concatenate([[0], np.cumsum(sizes[chosen])[:-1]])] = True
            local, back = np.unique(codes[places], return_inverse=True)
            flat = np.concatenate([cells_of[i][0] for i in local])
            owner = np.repeat(np.arange(len(local)), [len(cells_of[i][0]) for i in local])
            entry = np.array([cells_of[i][1] for i in local])
            emission = np.zeros((len(local), k))
            for c in range(k):
                emission[:, c] = np.bincount(owner, chain.weights[flat, c], len(local))
            emission[entry >= 0] += chain.lexicon_weights[entry[entry >= 0]]
            marginals, moves = forward_backward(emission[back], starts, chain.start, chain.moves)
            wanted = np.zeros_like(marginals)
            wanted[np.arange(len(places)), gold[places]] = 1
            error = marginals - wanted
            per_word = np.stack([np.bincount(back, error[:, c], len(local)) for c in range(k)], axis=1)
            g_weights = np.stack([np.bincount(flat, per_word[owner, c], 1 << _BITS) for c in range(k)], axis=1)
            g_lexicon = np.zeros_like(chain.lexicon_weights)
            g_lexicon[entry[entry >= 0]] = per_word[entry >= 0]
            real = np.zeros((k, k))
            inner = ~starts
            np.add.at(real, (gold[places][np.flatnonzero(inner) - 1], gold[places][inner]), 1)
            t += 1
            grads = [g_weights, g_lexicon, error[starts].sum(axis=0), moves - real]
            for p, g, m, v, rate in zip(parts, grads, first, second, (0.03, 0.03, 0.03, 0.03), strict=True):
                g = g / len(places) * 100 + 1e-3 * p
                m += 0.1 * (g - m)
                v += 0.01 * (g * g - v)
                p -= (rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-6)).astype(p.dtype)
            np.clip(chain.moves, -6, 6, out=chain.moves)
    return chain


def label_block(texts: pa.Array, chain: Chain) -> tuple[np.ndarray, np.ndarray]:
    """(expected words of each language, words with letters) of each text."""
    ends, codes, distinct = split_words(texts, letter_table())
    lettered = np.fromiter((w.isalpha() or any(c.isalpha() for c in w) for w in distinct), bool, len(distinct))
    distinct = [w.lower() for w in distinct]
    n = len(codes)
    starts = np.zeros(n + 1, bool)
    begins = np.concatenate([[0], ends[:-1]])
    starts[begins] = True
    emission = chain.emissions(distinct)
    marginals, _ = forward_backward(emission[codes].astype(np.float64), starts[:n], chain.start, chain.moves)
    marginals = marginals * lettered[codes][:, None]
    total = np.concatenate([np.zeros((1, marginals.shape[1])), np.cumsum(marginals, axis=0)])
    words = np.concatenate([[0], np.cumsum(lettered[codes])])
    return total[ends] - total[begins], words[ends] - words[begins]


def held_out(doc_id: Column, parts: int, which: int) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % parts == which, F.lit(False))


def _train_rows(rows: list[tuple]) -> Chain | None:
    return train_chain([r[1] for r in rows], [r[2] for r in rows])


def fit_languages(documents: DataFrame, sample: int = 1500, longest: int = LONGEST, most_chars: int = MOST_CHARS) -> Chain | None:
    """A field learned on ``sample`` documents at most, of those that aren't held out.

    Texts of more than ``longest`` characters aren't learned from, and no more than
    ``most_chars`` characters are.
    """
    known = documents.select("doc_id", "text", "lang").where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out(F.col("doc_id"), 3, 1))
    known = known.where(F.length("text") <= longest)
    # At most ``sample`` keys, so the broadcast doesn't grow with the documents.
    rows = known.join(F.broadcast(chosen_keys(known, "doc_id", sample)), F.col("doc_id") == F.col("chosen"), "left_semi")
    return fit_in_task(rows, _train_rows, most_chars)


def language_labels(documents: DataFrame, chain: Chain | None, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The kept columns and lang_pred, score, for every whole text.

    A text that is null or has no letter is ``und`` with score 0, and so is every
    text if there was nothing to learn from.  The score is the expected share of
    the text's words in the predicted language; ties go to the first name.
    """
    names = chain.languages if chain else []

    def label(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(batch.schema.get_field_index("text"))
            said: list[str] = []
            scores: list[float] = []
            for _, block in blocks(texts, BLOCK):
                if chain is None:
                    said += ["und"] * len(block)
                    scores += [0.0] * len(block)
                    continue
                share, words = label_block(block, chain)
                best = share.argmax(axis=1)
                top = share[np.arange(len(best)), best] / np.maximum(words, 1)
                said += [names[i] if w else "und" for i, w in zip(best.tolist(), words.tolist(), strict=True)]
                scores += np.where(words > 0, np.clip(top, 0, 1), 0).tolist()
            rest = [batch.column(batch.schema.get_field_index(c)) for c in keep]
            yield pa.RecordBatch.from_arrays([*rest, pa.array(said, pa.string()), pa.array(scores, pa.float64())], names=[*keep, "lang_pred", "score"])

    rows = documents.select(*dict.fromkeys([*keep, "text"]))
    kept = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema if f.name in keep)
    return rows.mapInArrow(lean(label), f"{kept}, lang_pred string, score double")


def identify_languages(documents: DataFrame, sample: int = 1500) -> DataFrame:
    """Per document: doc_id, held_out, lang_pred, score.

    Learns from documents with a language whose crc32 of doc_id leaves another
    remainder than 1 by 3; a null doc_id isn't held out.  No rows give no rows.
    """
    labels = language_labels(documents, fit_languages(documents, sample))
    return labels.select("doc_id", held_out(F.col("doc_id"), 3, 1).alias("held_out"), "lang_pred", "score")
