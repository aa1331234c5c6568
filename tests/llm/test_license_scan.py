"""License scans: the guarantee of windows and bands, and results against brute force over all templates."""

import random

import numpy as np
import pytest

from hitcodec.llm import license_scan as LS
from hitcodec.llm.common import table
from hitcodec.llm.license_texts import TEXTS, templates
from hitcodec.llm.ngram_join import WORDS, _WordHash

SCHEMA = "doc_id long, text string, found string, matches int, template string"


def brute(text, index):
    """Every template verified, without windows or bands."""
    found = WORDS.findall((text or "").lower())
    grams = LS.ordered_grams(found, _WordHash())
    spans = [m.span() for m in WORDS.finditer(text or "")]
    kept = LS.settle(LS.matches(found, grams, list(range(len(index.names))), index))
    return [(m[4], spans[m[0]][0], spans[m[1] + LS.GRAM - 1][1], m[2] / m[3]) for m in kept]


@pytest.fixture(scope="module")
def index():
    return LS.build_index(templates())


def test_bands():
    assert (1 - (2 / 3) ** LS.ROWS) ** LS.BANDS <= 1e-4 < (1 - (2 / 3) ** LS.ROWS) ** (LS.BANDS - 1)
    assert LS.bands_for(0.5, 3, 1e-3) == 52
    assert all(LS.width_for(k) in LS.WIDTHS and LS.width_for(k) <= max(1, k) for k in range(1, 2000))


def test_edited_copies_are_retrieved(index):
    rng = random.Random(5)
    tried = 0
    for t, (name, text) in enumerate(templates()):
        words = WORDS.findall(text.lower())
        whole = set(index.grams[t].values())
        for _ in range(3 if len(words) < 40 else 40):
            copy = list(words)
            for _ in range(rng.randint(0, max(1, len(words) // 20))):
                at = rng.randrange(len(copy))
                kind = rng.choice("isd")
                copy[at : at + (kind != "i")] = [] if kind == "d" else [f"w{rng.random()}"]
            if len({tuple(copy[i : i + LS.GRAM]) for i in range(len(copy) - LS.GRAM + 1)} & whole) < 0.8 * len(whole):
                continue
            tried += 1
            copy = [f"x{rng.random()}" for _ in range(rng.randrange(9))] + copy + ["y"] * 9
            _, _, owner = LS.retrieve(LS.ordered_grams(copy, _WordHash()), index)
            assert t in owner, (name, copy)
    assert tried > 500


@pytest.mark.parametrize("seed", range(20))
def test_regions(seed):
    rng = random.Random(seed)
    k = rng.randint(1, 12)
    at = sorted(rng.sample(range(120), rng.randint(1, 80)))
    which = [rng.randrange(k) for _ in at]
    need, span = int(np.ceil(0.8 * k - 1e-9)), max(k, int(1.25 * k))
    got = LS.regions(at, which, k)
    held = lambda a, b: len({w for x, w in zip(at, which) if a <= x <= b})
    assert all(need <= n == held(a, b) and b - a < span for a, b, n in got)
    assert all(x[1] < y[0] for x, y in zip(got, got[1:]))
    for a in range(120):  # no region that would do lies apart from those found
        if held(a, a + span - 1) >= need:
            assert any(x[0] <= a + span - 1 and x[1] >= a for x in got)


def test_settle():
    made = [(0, 9, 10, 10, "b"), (0, 9, 10, 12, "a"), (5, 20, 16, 16, "c"), (21, 22, 2, 2, "d"), (21, 22, 2, 2, "d"), (30, 31, 2, 2, "f"), (30, 31, 2, 2, "e")]
    assert LS.settle(made) == [(5, 20, 16, 16, "c"), (21, 22, 2, 2, "d"), (30, 31, 2, 2, "e")]


def texts():
    mit = TEXTS["MIT"]
    return [
        (1, mit), (1, mit), (2, None), (3, ""), (4, "one two three four"), (None, "é Released  under\nthe MIT License."), (5, mit.replace("restriction", "limits") + "\n" + TEXTS["ISC"]),
        (6, ("Released under the MIT License. " * 2000) + "end"), (7, "plain words and nothing else at all " * 20_000), (8, TEXTS["BSD-3-Clause"]), (9, TEXTS["BSD-2-Clause"]),
        (10, "Licensed under the GNU General Public License, version 3."), (11, "not released under any MIT License"), (12, " ".join(mit.split()[:60])),
    ]


def found(df):
    return sorted((str(r["doc_id"]), [tuple(m) for m in r["matches"]]) for r in df.collect())


def test_cases(spark, index):
    docs = spark.createDataFrame([(i, t, "f", 1, "t") for i, t in texts()], SCHEMA).repartition(3)
    got = found(LS.license_scan(docs))
    assert got == sorted((str(i), brute(t, index)) for i, t in texts())
    names = {i: [m[0] for m in ms] for i, ms in got}
    assert names["1"] == ["MIT"] and names["5"] == ["MIT", "ISC"] and len(names["6"]) == 2000
    assert names["8"] == ["BSD-3-Clause"] and names["9"] == ["BSD-2-Clause"] and names["10"] == ["GPL-3.0"]
    assert not any(names[i] for i in ("2", "3", "4", "7", "11", "12")) and names["None"] == ["MIT"]
    assert found(LS.license_scan(docs, block_grams=400)) == got
    digest = {r["doc_id"]: r for r in LS.license_digest(LS.license_scan(docs)).collect()}
    assert digest[None]["spans"] == "MIT:2:33" and digest[5]["licenses"] == "ISC,MIT" and digest[5]["n_matches"] == 2 and digest[2]["spans"] == ""


def test_empty_table_and_short_templates(spark):
    assert LS.license_digest(LS.license_scan(spark.createDataFrame([], SCHEMA))).collect() == []
    with pytest.raises(ValueError):
        LS.build_index([("x", "four words are few")])


def test_on_given(spark, sf, index):
    docs = table(spark, sf, "documents")
    want = sorted((str(r["doc_id"]), brute(r["text"], index)) for r in docs.collect())
    assert found(LS.license_scan(docs)) == want
    assert any(m for _, m in want)
