"""The search goes on while a round gains, however many rounds that takes."""

from augspark import catalog as cat
from augspark.catalog import Dataset
from augspark.search.engine import Candidate, Search
from augspark.search.request import Request


def test_more_than_twenty_gains(spark):
    df = spark.createDataFrame([(1, 2.0, 3.0, 0), (2, 1.0, 5.0, 1)], "k int, x double, y double, fold int")
    names = [f"s{i:02d}" for i in range(25)]
    made = {n: Dataset(n, 0, ("k",), ("f",), n, 1, 1, None, None) for n in names}

    class Fixed(Search):
        def candidates(self, req, plan=None, found=None):
            return [Candidate("vertical", made[n], "k", "k") for n in names if ("vertical", n, "k") not in plan.used]

        def pick(self, plan, found, able, req):
            return found[0], {"cv_r2": 0.03 * (26 - len(found)), "theta": [0.0]}, 1

        def base(self, *_):
            return {"cv_r2": 0.0, "theta": [0.0]}

        def extend(self, plan, c, out=None):
            plan.used = {*plan.used, c.id}
            return plan

    c = cat.Corpus(spark)
    a = Fixed(c).run(Request(df, ["x"], "y", {"k": "k"}))
    assert [s.dataset for s in a.plan] == names and a.stopped == "no candidate"
    b = Fixed(c).run(Request(df, ["x"], "y", {"k": "k"}), max_rounds=3)
    assert len(b.plan) == 3 and b.stopped == "rounds"
