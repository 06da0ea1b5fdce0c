"""Queries take their rows from given tables."""

from patternldp.queries import relational
from patternldp.sources.views import table


def test_sequences_are_as_long_as_the_parts_say(spark, sf):
    got = relational.QUERIES["fn_sequence_eps"](spark, sf)
    assert got.agg({"n": "sum"}).first()[0] == table(spark, sf, "part").agg({"p_size": "sum"}).first()[0]
