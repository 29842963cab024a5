"""Fixed schemas of the engine's tables, as DDL."""

PLAN = (
    "round int, tile_id long, machine_id int, cx0 int, cy0 int, cx1 int, cy1 int, "
    "parent_ids array<long>, prev_machine_id int, born_round int, retired_round int"
)
POINT = "point_id long, ts timestamp, rnd int, x double, y double, cx int, cy int, tag string"
RANGE_QUERY = (
    "query_id long, qts timestamp, rnd int, subscriber_id long, x0 double, y0 double, x1 double, y1 double, "
    "cx0 int, cy0 int, cx1 int, cy1 int, tag string"
)
MARGINALS = "tile_id long, axis string, idx int, n double, q long, r long, span_q long, span_q_new long"
REPORT = "machine_id int, numerator double, r long"
DECISION = "round int, r_total double, stage int, decision string, repeats int, action string, donor int, receiver int"
