"""Schemas of the frames that operators pass to each other; fixed, never inferred."""

VEC = "id long, vec array<float>"
QRY = "qid long, vec array<float>"
KNN = "id long, nbrs array<struct<dist:double,nid:long>>"
ADJ = "id long, nbrs array<long>"
EDGE = "src long, rank int, dst long"
HIT = "qid long, rnk int, nid long, dist double"
STATS = "stage string, name string, value double"
