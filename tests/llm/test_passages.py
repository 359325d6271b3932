"""Repeated passages whose pieces are all short."""

import random
import re
import unicodedata

import pytest

from warpspan.llm import passages


def _prose(rng, n):
    return ["".join(rng.choice("abcdefgh") for _ in range(6)) for _ in range(n)]


@pytest.mark.parametrize("joint", ["\n", ". ", "! \n", " "])
@pytest.mark.parametrize("inside", [False, True])
def test_passage_of_short_pieces_goes(make_docs, joint, inside):
    rng = random.Random(3)
    pieces = [" ".join(_prose(rng, n)) for n in (5, 1, 7, 3, 11, 2, 6, 4, 9, 7)]
    passage = joint.join(pieces) + "."
    before, after = (" ".join(_prose(rng, 9)) + ". ", " " + " ".join(_prose(rng, 9)) + ".") if inside else ("", "")
    docs = [" ".join(_prose(rng, 30)) + ".\n" + passage, before + passage + after, " ".join(_prose(rng, 20))]
    left = {r.doc_id: r.text for r in passages.without_repeats(make_docs(docs)).collect()}
    assert left[1] == docs[0] and left[3] == docs[2]
    words = " ".join(pieces).split()
    stay = [w in left[2] for w in words]
    # All of it but for its first and last few words.
    w = passages.WINDOW
    assert not any(stay[w - 1 : -2 * w + 1])
    assert before.strip(" .") in left[2] and after.strip(" .") in left[2]


def test_every_long_copy_is_found_whatever_stands_around_it(make_docs):
    rng = random.Random(5)
    docs = []
    for k in range(60):
        passage = _prose(rng, 51)
        odd = [w.upper() + rng.choice([" ", "  ", ", ", "\n"]) for w in passage]
        docs += [" ".join(_prose(rng, rng.randint(0, 40)) + passage + _prose(rng, rng.randint(0, 40))), " ".join(_prose(rng, rng.randint(0, 40))) + " " + "".join(odd) + "é " + " ".join(_prose(rng, rng.randint(0, 40)))]
    found = passages.repeated(make_docs(docs)).collect()
    assert {r.doc_id for r in found} == set(range(2, 121, 2)) and all(r.kept_id == r.doc_id - 1 and passages.PASSAGE_WORDS <= r.words <= 51 for r in found)


def test_short_copies_stay_and_texts_under_one_id_are_apart(make_docs):
    rng = random.Random(4)
    line, passage = " ".join(_prose(rng, 25)), " ".join(_prose(rng, 60))
    docs = [(1, line + "\n" + " ".join(_prose(rng, 50))), (2, line + "\n" + " ".join(_prose(rng, 50))), (3, passage), (3, "x " + passage), (None, passage), (5, passage), (5, passage)]
    found = [(r.doc_id, r.mark) for r in passages.repeated(make_docs(docs)).collect()]
    assert sorted((i or 0) for i, _ in found) == [0, 3, 5] and len(set(found)) == 3


def test_units_equal_a_plain_version(odd_texts):
    """Marks and units by trying every window, and equal digests only for equal words."""
    seen: dict = {}
    for text in [*odd_texts, "Ünder ½ ﬁne İstanbul " * 20, "a\U00010400b c " * 30]:
        units = passages.units_of(text).tolist()
        starts, ends, hashes = passages.words_hashed(text) if text else ([], [], [])
        words = [unicodedata.normalize("NFKC", m.group().lower()) for m in re.finditer(r"[^\W_]+", text or "")]
        assert len(words) == len(hashes)
        marks = sorted({max(range(k, k + passages.WINDOW), key=lambda j: (-int(hashes[j]), j)) for k in range(len(words) - passages.WINDOW + 1)}) if len(words) >= 24 else []
        assert marks == (passages.marks_in(hashes).tolist() if len(words) >= 24 else [])
        wanted = {(m, min(x for x in marks if x >= m + 24)) for m in marks[:400] if marks[-1] >= m + 24}
        reported = {(u[2], u[3]) for u in units}
        alike = {(u[5], u[6]) for u in units}
        assert len(alike) < len(units) or len(words) > 5000 or wanted <= reported or len({tuple(words[a:b]) for a, b in wanted}) < len(wanted)
        for start, after, first, last, _, *digest in units[:2000]:
            assert start == starts[first] and after == ends[last - 1] and last - first >= 24
            assert seen.setdefault(tuple(digest), tuple(words[first:last])) == tuple(words[first:last])
    assert len(set(seen.values())) == len(seen)
