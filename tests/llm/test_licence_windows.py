"""Licence notices that have become longer."""

import pytest

from splitguard.llm import licences


@pytest.mark.parametrize("extra, least", [(0, 1.0), (20, 0.87), (35, 0.81)])
def test_a_notice_with_words_in_its_middle_is_found_whole(extra, least):
    words = licences.NOTICES["MIT"][2].split()
    text = " ".join(["lead", "in", *words[:43], *(f"new{i}" for i in range(extra)), *words[43:], "then", "after"])
    (found,) = [x for x in licences.Scanner().scan(text) if x[0] == "MIT"]
    assert found[1] >= least
    assert text[found[2] : found[3]].startswith("Permission is") and text[found[2] : found[3]].endswith("the Software")
