"""Schemas of the frames that operators exchange; all are keyed by sample_id."""

SAMPLES = "sample_id long, vec array<double>, label int"
NODES = "sample_id long, vec array<double>, score double, last_step long"
KNN = "src long, dst long, d2 double, rank int"
EDGES = "src long, dst long, d2 double, w double"
PICKS = "round int, sample_id long, gain double"
HISTORY = "sample_id long, step long, score double"
