import pyarrow as pa
import pytest

from ptree_rules.llm.common import _WHILE_WRITING, giving_back, written


def test_batches_of_a_write_are_bounded_by_bytes(spark):
    """Also with the session's own settings put back after a write, and after one that fails."""
    docs = spark.range(0, 40, 1, 1).selectExpr("id", "repeat('x', 1000000) as text")
    before = {k: spark.conf.get(k, None) for k in _WHILE_WRITING}

    def sizes(batches):
        for batch in batches:
            yield pa.record_batch([pa.array([batch.num_rows], pa.int64())], ["n"])

    got = [r.n for r in written(docs.mapInArrow(giving_back(sizes), "n long"), "sizes").collect()]
    assert sum(got) == 40 and max(got) <= 10
    assert {k: spark.conf.get(k, None) for k in _WHILE_WRITING} == before
    with pytest.raises(Exception, match="USER_RAISED|wrong"):
        written(docs.selectExpr("raise_error('wrong') as x"), "fails")
    assert {k: spark.conf.get(k, None) for k in _WHILE_WRITING} == before
