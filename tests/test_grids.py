"""What grids do once, and what their measures do with events that no place sees."""

import random
from fractions import Fraction

from placeminer.functions.places import END, START
from placeminer.operators import conformance, lp
from placeminer.operators.compose import Implicit
from placeminer.operators.evaluate import SparkLog
from placeminer.operators.kernel import Block
from placeminer.plans.config import Config
from placeminer.plans.experiment import grid
from placeminer.workloads import ready


def test_each_candidate_of_a_grid_is_composed_once(spark, sf, monkeypatch):
    p = ready(spark, sf, "conv")
    single = {d: sorted(map(tuple, grid(p, Config(log="conv"), (0.8, 0.5), (d,), quality=False).where("oracle <> 'shared'").drop("t_search", "t_post").collect())) for d in (2, 3, 4)}
    asked, plain = [], Implicit.consume
    monkeypatch.setattr(Implicit, "consume", lambda self, c: asked.append((id(self), c.place)) or plain(self, c))
    rows = grid(p, Config(log="conv"), (0.8, 0.5), (4, 2, 3), quality=False).where("oracle <> 'shared'").drop("t_search", "t_post").collect()
    assert sorted(map(tuple, rows)) == sorted(sum(single.values(), []))
    assert len(asked) == len(set(asked)) and len({i for i, _ in asked}) <= 4  # one composer a threshold and oracle


def test_dominance_and_support_from_kept_answers():
    rng = random.Random(3)
    seqs = list({(0, *(rng.randint(1, 4) for _ in range(rng.randint(0, 9))), 5) for _ in range(40)})
    block = Block(seqs, [rng.randint(1, 5) for _ in seqs], 6)
    some = lambda: tuple(sorted(rng.sample(range(6), rng.randint(1, 3))))
    places = [(some(), some()) for _ in range(20)]
    t = block.token_states(places)
    below = (t[:, None, :] <= t[:, :, None]).all(axis=0)
    assert (block.dominance(places) == below).all()
    less, more = block.beside(places[0], places[1:])
    assert (less == below[0, 1:]).all() and (more == below[1:, 0]).all()
    for k in (1, 2, 5, 5, 3):
        part = rng.sample(places, k)
        assert block.support(part) == int(block.freq[block.fits(part).all(axis=1)].sum())


def test_linear_programs_stay_exact_beyond_64_bits():
    rows = [[3**30, 1, 0], [0, 3**25, 2], [7, 0, 3**20]]
    x = lp.feasible(rows, ["=", "=", "="], [5, 7, 11])
    assert all(sum(a * v for a, v in zip(r, x)) == b for r, b in zip(rows, (5, 7, 11))) and all(isinstance(v, Fraction) for v in x)
    assert lp.feasible([[1, 1]], [">="], [1]) is not None and lp.feasible([[1], [1]], ["=", "="], [1, 2]) is None


def test_alignments_pass_over_events_of_no_place(spark):
    labels = [START, "a", "x", "y", END]
    rows = [(i, [0, 1, *[2, 3][i % 2 :] * k, 1, 4], 2) for i, k in enumerate((40, 50, 60))]
    log = SparkLog(spark.createDataFrame(rows, "variant_id long, seq array<int>, freq long"), labels)
    place = [((0,), (1,))]
    found = conformance.alignment(log, place, 0, 4, states=30).orderBy("variant_id").collect()
    # The second a is one event too many; before, the free events alone passed the cap.
    assert [(r["cost"], r["trace_len"]) for r in found] == [(1, len(s)) for _, s, _ in rows]
    n = [len(s) for _, s, _ in rows]
    assert conformance.alignment_fitness(log, place, 0, 4, states=30) == sum(2 * (1 - 1 / (k + found[0]["model_len"])) for k in n) / 6
