"""Words of conversations are counted by role, and the workload is judged by all three scores."""

import pandas as pd

from corrsentry import catalog
from corrsentry.catalog.experiments import conversation_cells


def test_a_word_of_two_roles_is_two_features(spark, tmp_path):
    rows = [(i, 0, role, text) for i in range(0, 24, 4) for role, text in (("user", f"tea tea w{chr(97 + i)}"), ("assistant", "tea"), (None, "tea"))]
    pd.DataFrame(rows, columns=["conv_id", "turn", "role", "text"]).to_parquet(tmp_path / "conversations.parquet")
    got = {(r.feature, r.x) for r in conversation_cells(spark, str(tmp_path)).where("entity = 4").collect()}
    assert got == {("user:tea", 2), ("user:we", 1), ("assistant:tea", 1), (":tea", 1)}
    found = catalog.queries()["workload_conversations"](spark, str(tmp_path)).collect()
    assert {(r.win_id, r.detector, r.n) for r in found} == {(0, d, 6) for d in ("direct", "sampled", "block")}
