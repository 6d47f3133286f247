"""One small test for each finding of a review that led to a change in the training-data operators."""

from types import SimpleNamespace


def test_packing_gives_the_dictionaries_back(monkeypatch):
    """op8: the worker that packs no longer holds what it tokenised with."""
    from entitygraph.llm import packing, tokens

    monkeypatch.setattr(packing, "TaskContext", SimpleNamespace(get=lambda: SimpleNamespace(partitionId=lambda: 0)))
    tokens.encoder(tokens.vocabulary())
    assert list(packing._pack(8)(iter([]))) == [] and not tokens._encoders
