import pytest

from forestmine import pattern as pt
from forestmine.sources.generator import parse_tree


def test_parse_and_code_round_trip():
    code = "conv@0 user@1 assistant@2 user@1"
    assert pt.code(pt.parse(code)) == code
    assert pt.rightmost_path(pt.parse(code)) == [0, 3]
    assert pt.attach_depths(pt.parse(code)) == [0, 1, 0]


@pytest.mark.parametrize("bad", ["a@1", "a@0 b@2", "a@0 b@0"])
def test_parse_rejects_what_is_no_tree(bad):
    with pytest.raises(ValueError):
        pt.parse(bad)


def test_escaping_is_reversible():
    for label in ("a b", "x@y", "50%", "%20", ""):
        assert pt.unescape(pt.escape(label)) == label


def test_extension_adds_a_last_child_of_the_root():
    p1 = pt.parse("a@0 b@1 d@1")  # its rightmost path is a, d
    assert pt.code(pt.extend(p1, "a", 0)) == "a@0 b@1 d@1 a@1"
    assert len(pt.extensions(p1, ["a", "b"])) == 4
    with pytest.raises(ValueError):
        pt.extend(p1, "a", 2)


def test_one_removed_lifts_children_and_keeps_a_forking_root():
    assert {pt.code(n) for n in pt.one_removed(pt.parse("a@0 b@1 c@2"))} == {"a@0 b@1", "a@0 c@1", "b@0 c@1"}
    assert {pt.code(n) for n in pt.one_removed(pt.parse("a@0 b@1 c@1"))} == {"a@0 b@1", "a@0 c@1"}


def test_numbering_example():
    scopes = {lo: hi for lo, hi, _, _ in parse_tree("x(x,x,x(x,x))")}
    assert (scopes[0], scopes[1], scopes[5]) == (5, 1, 5)
