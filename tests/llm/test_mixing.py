import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from treefacts.llm import mixing


@settings(max_examples=40, deadline=None)
@given(st.dictionaries(st.sampled_from("abcdefgh"), st.tuples(st.integers(1, 300), st.floats(0.001, 50)), min_size=1, max_size=6))
def test_every_slot_is_within_one_block_of_the_weights(sources):
    blocks, weights = {s: n for s, (n, _) in sources.items()}, {s: w for s, (_, w) in sources.items()}
    phases, slots = mixing.schedule_slots(blocks, weights)
    assert sorted(x for own in slots.values() for x in own.tolist()) == list(range(sum(blocks.values())))
    for p, end in zip(phases, [*(x.start for x in phases[1:]), sum(blocks.values())], strict=True):
        for s, w in p.weights.items():
            given = np.searchsorted(slots[s], np.arange(p.start, end + 1)) - p.first[s]
            assert all(abs(int(n) - t * w) < 1 for t, n in enumerate(given))


def test_weights_are_exact_over_a_long_mix():
    for weights in ({"a": 0.7, "b": 0.2, "c": 0.1}, {"a": 0.9995, "b": 0.0005}, {"a": 1 / 3, "b": 0.123456789, "c": 1e-4}):
        total = sum(weights.values())
        _, slots = mixing.schedule_slots(dict.fromkeys(weights, 100_000), weights)
        t = np.arange(1, 100_001)
        for s, w in weights.items():
            assert np.abs(np.searchsorted(slots[s], t) - t * (w / total)).max() < 1 + 1e-9


def test_blocks_stay_bounded():
    blocks = lambda n: -(-n // max(mixing.BLOCK_DOCS, -(-n // mixing.MOST_BLOCKS)))
    assert max(map(blocks, (10**3, 10**7, 10**12))) <= mixing.MOST_BLOCKS


def test_mix_is_a_permutation_with_small_deviation(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet").select("doc_id", "source")
    weights = {"src0": 3.0, "src1": 1.0}
    rows = sorted(mixing.mix(docs, weights, block_docs=2).collect(), key=lambda r: r.mix_position)
    assert [r.mix_position for r in rows] == list(range(docs.count()))
    assert len({r.doc_id for r in rows}) == len(rows)
    assert all(r.mix_release <= r.mix_slot < r.mix_deadline for r in rows)
    slots = {}
    for r in rows:
        assert slots.setdefault(r.mix_slot, (r.source, r.mix_block)) == (r.source, r.mix_block)
    assert sorted(slots) == list(range(len(slots)))


def test_odd_rows(odd, none):
    rows = mixing.mix(odd).collect()
    assert sorted(r.mix_position for r in rows) == list(range(11))
    assert mixing.mix(none).count() == 0
    assert mixing.in_order(odd.drop("mix_position")).count() == 11
