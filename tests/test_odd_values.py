import duckdb

import __spark_entry__ as E
from tests.conftest import SMALL


def test_best_regions_users_with_missing_values_and_nan(spark, tmp_path):
    """Missing values are gaps, at a series' end too; NaN is the greatest value, of equal ones the digest decides."""
    con = duckdb.connect()
    value = "case when event_id % 7 = 0 then null when event_id % 7 = 1 then 'nan'::double else floor(value / 10) end"
    con.sql(f"copy (select event_id, ts, user_id % 40 as user_id, event_type, {value} as value, props from '{SMALL}/events.parquet' where event_id % 3 = 0) to '{tmp_path}/events.parquet' (format parquet)")
    con.sql(f"create view events as select * from '{tmp_path}/events.parquet'")
    want = con.sql(E.oracle_sql()["best_regions_users"]).fetchall()
    got = [tuple(r) for r in E.queries()["best_regions_users"](spark, str(tmp_path)).collect()]
    assert len(want) == 40 and sorted(got) == sorted(want)


def test_best_regions_vectors_with_missing_values_other_lengths_and_repeated_ids(spark, tmp_path):
    """Every vector is scored by the law of 64 points; missing values are its greatest, above NaN; rows of one id count together."""
    con = duckdb.connect()
    odd = "case when (vec_id + i) % 11 = 0 then null when (vec_id + i) % 11 = 1 then 'nan'::float when (vec_id + i) % 11 = 2 then -0.0::float when (vec_id + i) % 11 < 5 then floor(x * 4) else x end"
    kinds = {
        "missing": f"(select list(({odd})::float order by i) from (select unnest(embedding) x, unnest(range(64)) i))", "none": "[null::float for i in range(64)]", "no_vector": "null",
        "short": "embedding[1 : vec_id % 64]", "long": "embedding || embedding || embedding[1 : vec_id % 64]",
    }
    parts = [f"select vec_id, {v} as embedding, label from small where vec_id % 7 = {k}" for k, v in enumerate([*kinds.values(), "embedding", "embedding"])]
    again = "select vec_id, embedding[2:] as embedding, label from small where vec_id % 9 = 0 union all select null, embedding, label from small where vec_id = 1"
    con.sql(f"create view small as select * from '{SMALL}/embeddings.parquet' where vec_id < 280")
    con.sql(f"copy ({' union all '.join([*parts, again])}) to '{tmp_path}/embeddings.parquet' (format parquet)")
    con.sql(f"create view embeddings as select * from '{tmp_path}/embeddings.parquet'")
    want = con.sql(E.oracle_sql()["best_regions_vectors"]).fetchall()
    got = [tuple(r) for r in E.queries()["best_regions_vectors"](spark, str(tmp_path)).collect()]
    assert len(want) > 230 and sorted(got) == sorted(want)
