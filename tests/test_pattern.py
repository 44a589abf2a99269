import random

import pytest

from canopy.pattern import canonical, codec, expand, morph
from canopy.pattern.codec import parse, show
from canopy.pattern.model import Pattern, single
from tests.oracle import brute


def random_tree(rng, size, labels="abcd"):
    parent = [-1]
    path = [0]
    for n in range(1, size):
        del path[rng.randint(1, len(path)) :]
        parent.append(path[-1])
        path.append(n)
    return Pattern(tuple(rng.choice(labels) for _ in range(size)), tuple(parent))


def test_codec_round_trip_and_errors():
    for text in ("A", "A(B,C(D))", "flag=R(x:1)", "A(B(C),B)"):
        assert show(parse(text)) == text
    assert codec.parse_edges("A(/B,C//D)")[1] == (False, True, False, False)
    assert show(parse("A//B/C")) == "A(B(C))"
    for bad in ("", "A(", "A(B", "A)B", "A(,B)"):
        with pytest.raises(ValueError):
            parse(bad)
    assert codec.dot(parse("A(B)")).count("->") == 1


def test_model():
    p = parse("A(B(C),D)")
    assert (p.size, p.depth, p.fanout, p.leaves, p.attach_pos, p.rightmost_path) == (4, 2, 2, [2, 3], 0, [0, 3])
    assert p.prefix() == parse("A(B(C))") and p.subtree(1) == parse("B(C)") and not p.is_path
    with pytest.raises(ValueError):
        p.add(2, "x")
    with pytest.raises(ValueError):
        Pattern(("a", "b", "c"), (-1, 0, 2))


def test_order_puts_extensions_first():
    assert canonical.compare(parse("A(B)"), parse("A")) < 0
    assert canonical.compare(parse("A(B,C)"), parse("A(B)")) < 0
    assert canonical.compare(parse("A"), parse("B(A)")) < 0
    assert canonical.compare(parse("A(C)"), parse("A(B)")) > 0


def test_canonical_form_is_idempotent_and_prefix_closed():
    rng = random.Random(1)
    for _ in range(300):
        p = canonical.canonicalise(random_tree(rng, rng.randint(1, 8)))
        assert canonical.is_canonical(p)
        while p.size > 1:
            p = p.prefix()
            assert canonical.is_canonical(p)


def test_joins():
    assert expand.child_join(parse("A(B)"), parse("A(C)")) == parse("A(B(C))")
    assert expand.cousin_join(parse("A(B)"), parse("A(C)")) == parse("A(B,C)")
    assert expand.cousin_join(parse("A(B(C))"), parse("A(B,D)")) == parse("A(B(C),D)")
    # nothing is made if the left position is above the right one
    assert expand.child_join(parse("A(B,D)"), parse("A(B(C))")) is None and expand.cousin_join(parse("A(B,D)"), parse("A(B(C))")) is None


def test_expansion_is_ordered():
    members = [parse("A(B(C))"), parse("A(B(D))"), parse("A(B,C)")]
    by_left = {}
    for x, _, _, q in expand.expand_class(members):
        by_left.setdefault(x, []).append(q)
    for got in by_left.values():
        assert got == expand.class_order(got)


def test_subpatterns():
    p1, p2, p3, p4 = map(parse, ("A(B)", "A(B,C)", "A(B,C(D))", "X(A(B,C(D)))"))
    for p, q in ((p1, p2), (p2, p3), (p3, p4)):
        assert morph.iso_sub(p, q) and morph.embeds(p, q)
    assert morph.iso_sub(p1, p2, root=True) and not morph.iso_sub(p3, p4, root=True)
    skip = parse("X(D)")
    assert morph.embeds(skip, p4) and not morph.iso_sub(skip, p4)
    assert morph.root_images(parse("A(B,C)"), parse("A(A(B,C))")) == {0, 1}
    assert not morph.embeds(parse("A(B,C)"), parse("A(B(C))"))
    assert morph.embeds(parse("A(B(C))"), parse("A(B(C))"))


def test_embedding_against_brute_force():
    rng = random.Random(2)
    for _ in range(300):
        q, p = random_tree(rng, rng.randint(2, 7), "ab"), random_tree(rng, rng.randint(1, 4), "ab")
        assert morph.root_images(p, q) == {e[0] for e in brute.embeddings(p, q)}
        assert set(morph.maps(p, q)) == set(brute.embeddings(p, q))
        if morph.iso_sub(p, q):
            assert morph.embeds(p, q)


def test_neighbours():
    rng = random.Random(3)
    for _ in range(60):
        p = canonical.canonicalise(random_tree(rng, rng.randint(2, 6), "ab"))
        want = {q for q in brute.subpatterns(p) if q.size == p.size - 1}
        assert morph.one_smaller(p) == want
        for q in want:
            assert p in morph.one_larger(q, ["a", "b"])
    assert morph.one_smaller(parse("A(B)"), keep_root=True) == {single("A")}
