import os

from wdsum.llm import stored


def test_tables_are_kept_until_discarded(spark):
    df = stored.stored(spark.range(10))
    path = stored._written[-1].removeprefix("file:")
    assert df.count() == 10 and os.path.isdir(path)
    stored.discard(spark)
    assert not os.path.exists(path) and not stored._written


def test_a_mark_and_the_last_tables_are_kept(spark):
    first, mark = stored.stored(spark.range(3)), stored.written()
    paths = [stored.stored(spark.range(k)).inputFiles()[0].removeprefix("file:") for k in (1, 2, 3)]
    stored.discard(spark, mark, keep=1)
    assert [os.path.exists(p) for p in paths] == [False, False, True] and first.count() == 3
    stored.discard(spark)
    assert not os.path.exists(paths[2]) and stored.written() == 0
