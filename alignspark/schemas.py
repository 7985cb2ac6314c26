"""Fixed schemas of the relations that the operators exchange."""

SEQUENCES = "family string, seq_id bigint, seq string, len int"
PAIRS = "family string, i bigint, j bigint, a string, b string"
DISTANCES = "family string, i bigint, j bigint, distance double"
MERGES = "family string, step int, left int, right int, node int, left_len double, right_len double, height double, ids array<bigint>"
ALIGNED = "family string, seq_id bigint, aligned string"
PROFILE = "family string, pos int, symbol string, n bigint, freq double"
RESULTS = "family string, method string, root string, seed int, score bigint, cost double, width int, cells bigint, same_topology boolean, secs double"
GAP = "_"
