"""The matches under a cube of counts are made once."""

from patternlm.operators import measures as ms
from patternlm.operators.traverse import MATCHES


def test_the_cube_makes_its_matches_once(spark):
    made = spark.sparkContext.accumulator(0)

    def run(batches):
        for pdf in batches:
            made.add(len(pdf))
            yield pdf

    rows = [(0, i, [i], "", 0.0, 0.0, "", "", i % 2 == 0, i % 3, 0, 0) for i in range(6)]
    m = spark.createDataFrame(rows, MATCHES).mapInPandas(run, MATCHES)
    got = {(r["edited"], r["canonical"]): (r["n"], r["share"]) for r in ms.edit_encoding_cube(m).collect()}
    assert made.value == 6
    assert got == {(None, None): (6, 1.0), (True, None): (4, 0.666667), (False, None): (2, 0.333333), (None, True): (3, 0.5), (None, False): (3, 0.5), (True, True): (2, 0.333333), (True, False): (2, 0.333333), (False, True): (1, 0.166667), (False, False): (1, 0.166667)}
