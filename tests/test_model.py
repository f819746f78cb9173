from chronolode.functions import model as m
from chronolode.functions.udf import Extend, MatchEpisode


def test_key_round_trip_with_escapes():
    for e in ((("a",),), (("a", "b"), ("c",)), (("a+b",), ("c>d", "e\\f"))):
        assert m.parse(m.key(e)) == e


def test_concatenation_length_kind():
    e = m.s_extend(m.i_extend((("B",),), "A"), "C")
    assert e == (("A", "B"), ("C",)) and m.length(e) == 3 and m.size(e) == 2
    assert [m.kind(x) for x in ((("A",),), (("A", "B"),), (("A",), ("B",)), e)] == ["simple", "simultaneous", "serial", "complex"]


def test_subepisode_is_ordered_containment():
    b = (("A", "B"), ("C",), ("A", "C"))
    assert m.is_subepisode((("B",), ("A",)), b) and m.is_subepisode(b, b)
    assert not m.is_subepisode((("A", "C"), ("B",)), b) and not m.is_subepisode((("C",), ("C",), ("A",)), b)


def test_table_functions():
    assert list(MatchEpisode().eval(1, [1, 2, 3], ["A", "B", "C"], [5, 6, 7], "A>C")) == [(1, 3, 12)]
    assert list(MatchEpisode().eval(1, [1, 2], ["A", "B"], [5, 6], "B>A")) == []
    assert list(Extend().eval("A", ["A", "B"], ["A"])) == [("A+B",), ("A>A",)]
