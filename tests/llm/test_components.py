import random

import pytest

from veilmatch.llm.components import components


def by_hand(links):
    of = {}
    for x in {x for link in links for x in link}:
        of[x] = x
    moved = True
    while moved:
        moved = False
        for a, b in links:
            low = min(of[a], of[b])
            moved |= of[a] != low or of[b] != low
            of[a] = of[b] = low
    return of


@pytest.mark.parametrize("direct", [0, 1 << 20])
def test_smallest_node_of_every_component(spark, direct):
    rng = random.Random(direct)
    path = [(i * 7919 % 211 - 100, (i + 1) * 7919 % 211 - 100) for i in range(150)]
    loose = [(rng.randrange(1000, 1400), rng.randrange(1000, 1400)) for _ in range(180)]
    star = [(-(2**63), 2**62 + i) for i in range(40)]
    links = path + loose + star + star[:5]
    found = components(spark.createDataFrame(links, "a long, b long"), direct=direct).collect()
    linked = [(a, b) for a, b in links if a != b]
    assert len(found) == len({r["node"] for r in found})
    assert {r["node"]: r["label"] for r in found} == by_hand(linked)


@pytest.mark.parametrize("direct", [0, 1 << 20])
def test_no_links_no_rows(spark, direct):
    for links in ([], [(4, 4)]):
        out = components(spark.createDataFrame(links, "a long, b long"), direct=direct)
        assert out.columns == ["node", "label"] and not out.count()
