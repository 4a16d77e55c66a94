"""A hub's many URIs are rescored without visiting them one by one."""

import time

import pytest

from webtraverse.plans.approaches import APPROACHES, LITERAL_HYBRIDS
from webtraverse.plans.query import WORKLOAD
from webtraverse.plans.simulate import SubWeb, cell


def hub(n=4_000, each=3):
    """A nation with ``n`` customers, each with ``each`` orders; all links stand in the documents of both ends."""
    nation, = WORKLOAD["q2"].seeds()[1:2]
    docs = {nation: []}
    for c in range(n):
        customer = c * 16 + 3
        link = (customer, 2, nation)
        docs[nation].append(link)
        docs[customer] = [link]
        for k in range(each):
            order = (c * each + k) * 16 + 6
            docs[customer].append((order, 4, customer))
            docs[order] = [(order, 4, customer)]
    return SubWeb({d: sorted(t) for d, t in docs.items()})


@pytest.mark.parametrize("name", ["rcc1", "rcc2", "rel2", "partial_rcc1", "partial_rcc1_product", "pagerank"])
def test_a_hub_is_rescored_in_time(name):
    web = hub()
    began = time.time()
    run = cell(web, WORKLOAD["q2"], (APPROACHES | LITERAL_HYBRIDS)[name])
    assert sorted(run.trace) == sorted(web.documents) and len(run.solutions) == 4_000 * 3 * 4
    assert time.time() - began < 40
