"""Registry of the operators' queries and of the SQL that gives the same rows."""

from __future__ import annotations

from .decontam import op5_simhash_decontamination
from .media import op6_media_columns
from .mixing import op8_pfair_mix
from .neardup import SQL as NEARDUP_SQL
from .neardup import op7_minhash_neardup
from .quality import op4_quality_trees
from .revisit import SQL as REVISIT_SQL
from .revisit import op10_warc_revisits
from .shards import op1_kd_shards
from .substring import SQL as SUBSTRING_SQL
from .substring import op3_debruijn_substrings
from .toxicity import op2_toxic_segments
from .urlrep import SQL as URL_SQL
from .urlrep import op9_url_reputation

QUERIES = (op1_kd_shards, op2_toxic_segments, op3_debruijn_substrings, op4_quality_trees, op5_simhash_decontamination, op6_media_columns, op7_minhash_neardup, op8_pfair_mix, op9_url_reputation, op10_warc_revisits)


def queries() -> dict:
    return {f.__name__: f for f in QUERIES}


def oracle_sql() -> dict[str, str]:
    return {"op3_debruijn_substrings": SUBSTRING_SQL, "op7_minhash_neardup": NEARDUP_SQL, "op9_url_reputation": URL_SQL, "op10_warc_revisits": REVISIT_SQL}
