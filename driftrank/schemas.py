"""Fixed schemas of the engine's tables."""

EDGES = "src long, dst long"
EDGE_EVENTS = "seq long, src long, dst long, op int, ts timestamp"
STATE = "root long, node long, est double, res double"
PPR = "root long, node long, ppr double"
WALKS = "root long, walk_id long, path array<long>, stuck boolean, epoch int"
TRACE = "method string, root long, seq long, residual_updates long, push_iterations long, push_cost long, repair_abs double, rounds int, seconds double"
SINK = -1  # node that collects what a vertex without out-edges cannot pass on
EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
