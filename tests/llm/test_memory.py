"""A worker serves all stages of a chain, and holds the tables of one operator at a time."""

from steerselect.llm import packing, toxicity
from steerselect.llm.common import begin
from steerselect.llm.queries import vocabulary


def test_a_worker_forgets_the_tables_of_the_operator_before():
    begin("toxicity", toxicity.forget)
    toxicity.features("some words of a text")
    begin("toxicity", toxicity.forget)
    assert len(toxicity._cache) == 5  # tasks of one operator share them
    begin("packing", packing.encoder.cache_clear)
    assert not toxicity._cache and not toxicity._cache.old
    packing.encoder(vocabulary("word_bpe_49k.json")).encode("some words")
    begin("similar")
    assert packing.encoder.cache_info().currsize == 0
