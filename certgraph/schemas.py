"""Column layouts that the operators exchange, as DDL strings."""

EDGE = "seq long, u long, v long"
VERTEX = "id long"
POSITION = "id long, comp long, pos long"
FOREST = "layer int, child long, parent long, parent_pos long, seq long"
CERTIFICATE = "seq long, u long, v long, layer int"
PAIR = "u long, v long, kappa int"
SEPARATOR = "l int, members array<long>, pieces int"
VERDICT = "k int, verdict boolean, reason string, witness array<long>"
