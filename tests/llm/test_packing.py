"""Fillings against brute force, and packing at the size of production groups."""

from __future__ import annotations

import collections
import itertools

import numpy as np
import pyarrow as pa

from logsketch.llm import packing


def test_bin_completion_at_the_size_of_groups():
    x = np.random.default_rng(0).integers(700, 1600, 1500)
    got = packing.complete(x, 4096)
    assert sorted(k for s in got for k in s) == list(range(len(x))) and all(x[s].sum() <= 4096 for s in got)
    assert len(got) < len(packing.best_fit(x, 4096)) - 5


def test_fillings_are_all_that_no_other_dominates():
    """Any number of pieces: a filling goes only where a left-over piece could replace some of its pieces, and the best sum comes first."""
    r = np.random.default_rng(2)
    for _ in range(60):
        x = sorted(r.integers(1, 14, r.integers(1, 9)).tolist())
        count, room = np.bincount(x, minlength=31), int(r.integers(8, 31))
        every = {c for n in range(len(x) + 1) for c in itertools.combinations(x, n) if sum(c) <= room}

        def worse(c):
            rest = collections.Counter(x) - collections.Counter(c)
            return any(sum(s) <= u <= sum(s) + room - sum(c) and s != (u,) for u in rest for n in range(len(c) + 1) for s in itertools.combinations(c, n))

        got = [tuple(sorted(f)) for f in packing._fillings(count, room, room, [10**6])]
        assert len(got) == len(set(got)) and set(got) == {c for c in every if not worse(c)}
        assert [sum(f) for f in got] == sorted((sum(f) for f in got), reverse=True)


def test_few_pieces_are_packed_into_as_few_sequences_as_can_be():
    r = np.random.default_rng(5)

    def fits(pieces, free):
        if not pieces:
            return True
        tried = set()
        for k, room in enumerate(free):
            if room >= pieces[0] and room not in tried:
                tried.add(room)
                if fits(pieces[1:], [*free[:k], room - pieces[0], *free[k + 1 :]]):
                    return True
        return False

    for _ in range(150):
        capacity = int(r.integers(8, 60))
        x = r.integers(1, capacity + 1, r.integers(1, 13))
        least = next(n for n in range(1, 14) if fits(sorted(x.tolist(), reverse=True), [capacity] * n))
        assert len(packing.complete(x, capacity)) == least


def test_groups_of_production_size_are_searched(monkeypatch):
    """More fillings are taken back and tried anew than one descent has."""
    x = np.random.default_rng(0).integers(820, 1400, 8192)
    seen = []
    plain = packing._options
    monkeypatch.setattr(packing, "_options", lambda *a: (seen.append(1), plain(*a))[1])
    got = packing.complete(x, 4096)
    assert len(seen) > len(got) + 1000 and len(got) < len(packing.best_fit(x, 4096))


def test_ids_are_the_tokenizer_s():
    from tokenizers import Tokenizer

    from logsketch.llm import textkernel as K

    texts = ["it's 'sir don't x'S 12a3 a1b2 '''s !'s", "a<|endoftext|>b", "\u0130stanbul O\u2019Neil caf\u00e9's e\u0301a A\u030a", " x\u00a0y\u3000z a\x1cb\x85d", "", None, "word " * 70_000, "\u0000a\u0001b 've'VE 5's"]
    model, worker = Tokenizer.from_file(packing.tokenizer_path()), packing.Ids(packing.tokenizer_path())
    for _ in range(2):  # words unknown, then known
        for first, data, offsets in K.blocks(pa.array(texts)):
            ids, at = worker.rows(data, offsets)
            for k in range(len(offsets) - 1):
                assert ids[at[k] : at[k + 1]].tolist() == model.encode(texts[first + k] or "", add_special_tokens=False).ids


def test_the_tokenizer_gets_few_words_at_once(monkeypatch):
    """What a call holds until it returns grows with its words; the ids are the same."""
    text = pa.array(["".join(f"w{chr(97 + k % 26)}{chr(97 + k // 26 % 26)} z-{k} " for k in range(90)), None])
    data = next(packing.K.blocks(text))[1:]
    whole = packing.Ids(packing.tokenizer_path()).rows(*data)
    small = packing.Ids(packing.tokenizer_path())
    monkeypatch.setattr(packing, "CALL", 8)
    model, most = small.model, []

    class Model:
        def encode(self, text, **k):
            most.append(len(text.split()))
            return model.encode(text, **k)

        def encode_batch_fast(self, words, **k):
            most.append(len(words))
            return model.encode_batch_fast(words, **k)

    small.model = Model()
    got = small.rows(*data)
    assert max(most) <= 8 and all((a == b).all() for a, b in zip(got, whole, strict=True))
