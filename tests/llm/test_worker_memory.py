"""What tasks leave behind in the workers they ran in."""

from __future__ import annotations

import pyarrow as pa

from pathalgebra.llm import fitting, langid, memory, tokens, toxicity


class _Rows:
    """Stands for a frame; gives the function that its tasks would run."""

    schema = ()

    def select(self, *columns):
        return self

    def mapInArrow(self, work, schema):  # noqa: N802
        return work


def test_tables_of_another_operator_are_dropped():
    for work in (langid.language_labels(_Rows(), None, keep=()), toxicity.toxicity_scores(_Rows(), None, keep=())):
        tokens.shared_encoder(tokens.tokenizer_path())
        assert tokens._encoders
        list(work(iter(())))
        assert not tokens._encoders
    assert any(x is tokens._encoders for x in memory.caches)


def test_texts_are_labelled_in_small_blocks(monkeypatch):
    seen = []
    monkeypatch.setattr(langid, "label_block", lambda block, chain: (seen.append(len(block)), langid.np.ones((len(block), 1)))[1:] + (langid.np.ones(len(block), int),))
    chain = langid.Chain(["x"], None, None, None, None, None)
    batch = pa.RecordBatch.from_arrays([pa.array(["word " * 100_000] * 8)], names=["text"])
    found = list(langid.language_labels(_Rows(), chain, keep=())(iter([batch])))
    assert found[0].num_rows == 8 and sum(seen) == 8 and max(seen) <= 2


def _count(rows):
    return len(rows)


def test_no_rows_stay_beside_the_child(monkeypatch):
    held = []
    monkeypatch.setattr(fitting, "_in_own_process", lambda train, rows: (held.append(rows), b"")[1])
    work = {}

    class Frame(_Rows):
        columns = ("k", "t", "l")

        def where(self, *x):
            return self

        repartition = sortWithinPartitions = where  # noqa: N815

        def mapInArrow(self, run, schema):  # noqa: N802
            work["run"] = run
            return self

        def first(self):
            return {"model": fitting.pickle.dumps(None)}

    class Functions:
        def __getattr__(self, name):
            return lambda *x: type("C", (), {"isNotNull": lambda s: s, "__and__": lambda s, o: s})()

    monkeypatch.setattr(fitting, "F", Functions())
    fitting.fit_in_task(Frame(), _count)
    rows = [(3, "c", "l"), (1, "a", "l"), (2, "b", "l")]
    batch = pa.RecordBatch.from_arrays([pa.array(x) for x in zip(*rows, strict=True)], names=["k", "t", "l"])
    task = work["run"](iter([batch]))
    next(task)
    assert held[0] == sorted(rows)
    inner = task.gi_yieldfrom
    assert inner.gi_frame.f_locals["held"] is held[0]  # the list that the child's caller clears
