"""Fixed schemas of the engine's frames."""

EDGES = "src long, dst long"
ARCS = "src long, dst long, weight long"
ASSIGNMENT = "vid long, part int"
ROOM = "part int, cap long, load long, remaining long"
MOVES = "vid long, from_part int, to_part int, gain long, settle_iter int"
HISTORY = "iteration int, proposed long, damped long, refused long, moved long, cut long, edges long, max_load long, min_load long, step_ms long"
CHANGES = "seq long, op string, src long, dst long, priority int, ts timestamp"
CALLS = "event_id long, ts timestamp, src long, dst long"
