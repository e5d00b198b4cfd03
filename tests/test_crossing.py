"""Set-oriented projection and retraction against the kernel, for every type operation, both ways."""

import random

import pytest
from states import chosen, database, live_of, log, random_writes, rows_of, start, type_pool

from opframe.kernel.interp import apply, run
from opframe.kernel.rules import Blocked, project_all, retract
from opframe.operators import oplog

TYPES = type_pool()


@pytest.mark.parametrize("k", range(len(TYPES)))
def test_forward_equals_the_kernel(spark, k):
    over, state, ops = TYPES[k], start(), chosen(100 + k, 16)
    late, _ = project_all([over], ops, state=state)
    db = database(spark, state)
    got = rows_of(oplog.replay(db.apply(over), oplog.forward(log(spark, ops), over, db)))
    assert got == live_of(run(state, [over, *late])), (over, ops)


@pytest.mark.parametrize("k", range(len(TYPES)))
def test_backward_equals_the_kernel(spark, k):
    """Writes that depend on the type operation are blocked, all others arrive; only what relinking a split row means is the engine's alone."""
    over, state = TYPES[k], start()
    ops = [x for x in random_writes(apply(state, over), random.Random(k), 14) if "n_link" not in x.path]
    pres, blocked = [], []
    for i, x in enumerate(ops):
        try:
            pres += retract(over, x, state=state)[0]
        except Blocked:
            blocked.append(f"op{i + 1}")
    db = database(spark, state)
    ok, bad = oplog.backward(log(spark, ops), over, db if over.kind == "join_link" else db.apply(over))
    assert sorted(r.op_id for r in bad.collect()) == sorted(blocked)
    assert rows_of(oplog.replay(db, ok)) == live_of(run(state, pres))


def test_relinked_rows_take_the_columns_of_what_they_link_to(spark):
    """Strings and numbers alike; a link and a later write of what it names meet in the row."""
    from opframe.model import ops as o
    from opframe.model.types import ANY, NULL_LINK

    state, over = start(), o.split_table(("t", ANY, "n"), ("s",), ("n", "who"))
    db = database(spark, state)
    ops = [o.set_link(("t", "e0", "n_link"), "e1"), o.set_cell(("s", "e1", "n"), 40.0), o.set_link(("t", "e2", "n_link"), NULL_LINK)]
    ok, bad = oplog.backward(log(spark, ops), over, db.apply(over))
    got = rows_of(oplog.replay(db, ok))["t"]
    assert bad.count() == 0 and (got["e0"]["n"], got["e0"]["who"]) == (40.0, "p1") == (got["e1"]["n"], got["e1"]["who"]) and (got["e2"]["n"], got["e2"]["who"]) == (None, "")


def test_what_has_no_rule_is_refused(spark):
    from opframe.model import ops as o
    from opframe.model.types import ANY
    from opframe.operators.relation import Rejected

    db = database(spark, start())
    for over in (o.extract_list(("t", ANY, "l"), ("x",)), o.collapse_set(("t",), ("who",)), o.wrap_list(("t", ANY, "l")), o.wrap_record(("t", ANY, "r"), "q")):
        with pytest.raises(Rejected):
            oplog.forward(log(spark, chosen(1)), over, db)
