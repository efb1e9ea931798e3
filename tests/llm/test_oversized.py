"""Links of oversized clusters that join two components."""

import pytest

from labelroute.llm import neardup


@pytest.mark.parametrize("block,block_bytes", [(3, 1 << 20), (64, 8_000)])
def test_a_chain_is_one_component(spark, block, block_bytes):
    """Each text is linked with the next and with no other.  Blocks ask members of
    several places at once; links between members that two of them reached join
    the pieces."""
    rows = [(100 * c + i, " ".join(f"{'ab'[c]}{w}" for w in range(i * 12, i * 12 + 400))) for c in range(2) for i in range(8)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = neardup.components(df, 3, 85, cluster_docs=3, block=block, block_bytes=block_bytes).collect()
    assert {(r["doc_id"], r["component_id"]) for r in got} == {(d, d - d % 100) for d, _ in rows}
