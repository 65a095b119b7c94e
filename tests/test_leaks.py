"""No cleaning system may know how errors or clean records are made."""

import pathlib
import re

import pytest

import cellscrub.systems
from cellscrub.operators import inject
from cellscrub.systems import corrector_ensemble as c
from cellscrub.systems.record_prompt import RulebookCompleter

FILES = sorted(pathlib.Path(cellscrub.systems.__file__).parent.glob("*.py"))


@pytest.mark.parametrize("path", FILES, ids=lambda p: p.stem)
def test_systems_do_not_import_the_generators(path):
    text = path.read_text()
    assert not re.search(r"inject|sources\.tables|SHORT_FORMS|TRANSLATIONS|CORRUPTORS", text)
    assert not re.search(r"Annex|Zanzibar|misplaced entry|Nation", text)


def test_the_tables_are_the_injectors_own():
    from cellscrub.functions import dicts

    assert not hasattr(dicts, "SHORT_FORMS") and not hasattr(dicts, "TRANSLATIONS") and inject.SHORT_FORMS


def test_edits_are_learned_from_pairs():
    got = {(a, o, x, y) for a, o, x, y, _ in c.learned_edits([("road", "A Annex", "A"), ("road", "B-C", "B C"), ("name", "xfoo", "foo")])}
    assert ("road", "end", " Annex", "") in got and ("road", "any", "-", " ") in got and ("name", "start", "x", "") in got
    assert c.learned_edits([]) == []
    assert [c.edited("a-b", *e) for e in (("any", "-", " "), ("end", "b", ""), ("start", "x", "y"))] == ["a b", "a-", None]


def test_the_stand_in_only_normalises():
    answer = RulebookCompleter()._cell
    assert answer("road", "MAIN ROAD") == {"error": True, "value": "Main Road"} and answer("road", "Main Rd.")["value"] == "Main Road"
    assert answer("postcode", "12345") == {"error": False, "value": None} and answer("postcode", "1234")["error"]
    assert answer("country", None) == {"error": True, "value": None}
