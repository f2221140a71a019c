"""What workers keep between tasks."""

from __future__ import annotations

from logsketch.llm import common, packing


def test_workers_forget_what_other_modules_keep():
    """The tokenizer does not stay in a worker that scores languages."""
    packing.Ids.of["x"] = None
    assert list(common.lean(lambda batches: batches)([])) == [] and not packing.Ids.of
    packing.Ids.of["x"] = None
    own = packing._pieces("x", 1, 1)
    assert own.__module__ == packing.__name__ and list(common.lean(own)([])) == [] and "x" in packing.Ids.of
    packing.Ids.of.clear()
