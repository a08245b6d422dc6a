"""Streamed windows and sessions hold the rows of their batch twins, the last ones included."""

from collections import Counter

import pytest
from conftest import SF

from seqstat.streaming import stream


@pytest.mark.parametrize("name", ["stream_tumbling", "stream_sliding", "stream_session"])
def test_stream_against_twin(spark, name):
    found, want = (Counter(map(tuple, stream.queries()[n](spark, SF).collect())) for n in (name, f"{name}_batch"))
    print(name, sum(found.values()), sum(want.values()))
    assert found == want
