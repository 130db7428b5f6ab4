"""Restart snapshots: the newest complete version, whatever an interrupted save leaves."""

import pytest

from blockrecover.operators import persist


def test_interrupted_save_leaves_the_version_before(spark, tmp_path):
    folder = f"file://{tmp_path}/state"
    with pytest.raises(FileNotFoundError):
        persist.load(spark, folder)
    persist.save(spark, folder, {"a": spark.range(3), "b": spark.range(0)}, {"pass": 1})
    persist.save(spark, folder, {"a": spark.range(5)}, {"pass": 2})

    class Lost(Exception):
        pass

    class Broken:
        @property
        def write(self):
            raise Lost

    with pytest.raises(Lost):
        persist.save(spark, folder, {"a": spark.range(9), "b": Broken()}, {"pass": 3})
    tables, facts = persist.load(spark, folder)
    assert facts == {"pass": 2} and sorted(tables) == ["a"] and tables["a"].count() == 5
