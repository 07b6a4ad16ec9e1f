"""How a window join is carried out: value buckets, merge-rank, hash, nested loop."""
