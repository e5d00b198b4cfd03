"""Transfer and undo on both planes: two copies with type operations on either side end as the kernel's do."""

import pytest
from states import ROW, chosen, database, live_of, log, rows_of, start

from opframe import vcs
from opframe.kernel.interp import run
from opframe.kernel.rules import project_all
from opframe.model import ops as o
from opframe.model.types import Num, Str
from opframe.operators import oplog

PAIRS = [
    (o.wrap_list((*ROW, "who")), o.convert_type((*ROW, "n"), Str(), Num())),
    (o.split_table((*ROW, "n"), ("s",), ("n",)), o.wrap_record((*ROW, "who"), "R")),
    (o.move_field((*ROW, "what"), (*ROW, "r", "w")), o.drop_field(ROW, "n")),
]


@pytest.mark.parametrize("k", range(len(PAIRS)))
def test_sync_makes_both_copies_what_the_kernel_makes_them(spark, k):
    mine, theirs = PAIRS[k]
    s = start()
    left, right = [x for x in chosen(k, 5) if x.kind == "set_cell"], [x for x in chosen(50 + k, 5) if x.kind == "set_cell"]
    db = database(spark, s)
    a = vcs.Document("a", db, log(spark, left, 1)).alter(100, mine)
    b = vcs.Document("b", db, log(spark, right, 200).withColumn("op_id", oplog.F.concat("op_id", oplog.F.lit("b")))).alter(300, theirs)
    late, _ = project_all([*right, theirs], [*left, mine], state=s)
    want = live_of(run(s, [*right, theirs, *late]))
    got_a, got_b = (rows_of(x.state()) for x in vcs.sync(a, b))
    assert got_b == want and got_a == want


def test_type_operations_are_kept_in_a_log(spark, tmp_path):
    db = database(spark, start())
    line = [(1, o.convert_type((*ROW, "n"), Str(), Num())), (2, o.split_table((*ROW, "n"), ("s",), ("n", "who")))]
    rows = oplog.log_types(spark, line)
    assert oplog.types_of(rows) == line
    doc = vcs.Document("d", db, rows).append(log(spark, [o.set_cell(("s", "e0", "who"), "x")], 3))
    vcs.export_bundle(doc, str(tmp_path / "bundle"))
    again = vcs.import_bundle(spark, str(tmp_path / "bundle"), "d", db)
    assert rows_of(again.state()) == rows_of(doc.state()) and rows_of(doc.state())["s"]["e0"] == {"n": "0", "who": "x"}
