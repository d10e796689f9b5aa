"""Scalar neighbours: frames grow from their partition's begin, copies of values count once."""

import bisect

from vecspark.functions.ranking import scalar_neighbours


def test_neighbours_without_frames_to_the_end(spark):
    xs, vs = [5, 5, 9, 20, 20, 31], [0, 5, 6, 20, 25, 31, 40]
    got = scalar_neighbours(spark.createDataFrame([(x,) for x in xs], "x long"), spark.createDataFrame(list(enumerate(vs)), "qid long, v long"))
    assert "RangeFrame, currentrow$(), unboundedfollowing$()" not in got._jdf.queryExecution().optimizedPlan().toString()
    s = sorted(set(xs))
    want = [(i, v, *((s[bisect.bisect_right(s, v) - 1] if v >= s[0] else None), (s[bisect.bisect_left(s, v)] if v <= s[-1] else None))) for i, v in enumerate(vs)]
    assert sorted(map(tuple, got.select("qid", "v", "below", "above").collect())) == want
