import hashlib
import random
from collections import Counter

import pytest

from rankfeed.llm import repeats
from rankfeed.llm.runtime import ship, table
from tests.conftest import SF


def brute(rows):
    """(doc_id, bytes, removed, spans, digest) of each row, from a count of every window."""
    bodies = [(a, (b or "").encode()) for a, b in rows]
    seen = Counter(hash(x[k : k + 200]) for _, x in bodies for k in range(len(x) - 199))
    out = []
    for a, x in bodies:
        gone = bytearray(len(x))
        for k in range(len(x) - 199):
            if seen[hash(x[k : k + 200])] > 1:
                gone[k : k + 200] = b"\1" * 200
        kept = bytes(c for c, g in zip(x, gone, strict=True) if not g)
        runs = sum(g and not (k and gone[k - 1]) for k, g in enumerate(gone))
        out.append((a, len(x), sum(gone), runs, hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=str)


def got(docs, **more):
    return sorted((tuple(r) for r in repeats.removed(docs, **more).collect()), key=str)


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(3)
    word = lambda n: " ".join(f"w{rng.randrange(5000)}é" for _ in range(n))
    shared, longer = word(60), word(300)
    out = [(1, None), (2, ""), (3, "short"), (4, "short"), (None, word(50)), (5, "ab" * 3000), (6, "x" * 199), (7, "x" * 200), (8, "x" * 201), (9, word(4000))]
    out += [(k, f"{word(30)} {shared[k - 20 :]} {word(20)} {longer[: 20 * k]}") for k in range(20, 40)]
    out += [(50, out[9][1]), (50, out[9][1]), (51, word(90)), (51, word(90)), (52, out[12][1] + "tail")]
    return out


@pytest.mark.parametrize("most", [20000, 3])
def test_removed_matches_brute_force(spark, rows, most):
    docs = ship(spark).createDataFrame([(a, b, "k") for a, b in rows], "doc_id long, text string, key string")
    assert got(docs, most=most) == brute(rows)


def test_removed_on_given_table(spark):
    docs = table(spark, SF, "documents").select("doc_id", "text")
    assert got(docs) == brute([tuple(r) for r in docs.collect()])


def test_removed_of_no_rows(spark):
    assert got(ship(spark).createDataFrame([], "doc_id long, text string")) == []


def test_intervals_visit_children_first():
    assert list(repeats.intervals([2, 4, 4, 0, 3])) == [(1, 3, 4), (0, 3, 2), (4, 5, 3)]


def test_groups_have_all_occurrences():
    after, before = [b"aab", b"aab", b"aac", b"abc"], [b"zz", b"zy", b"zx", b"zz"]
    found = {(tuple(sorted(m.tolist())), left + right) for m, _, left, right in repeats.maximal_groups(after, before, 3)}
    assert ((0, 1, 2), 3) in found and ((0, 1), 4) in found and ((0, 3), 3) in found
