"""The rewrites: runs, pairs, leaves; their loop; its inverse; measures and baselines."""
