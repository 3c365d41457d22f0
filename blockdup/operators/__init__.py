"""DataFrame operators: blocks, index, detection, verification, types, groups, baselines."""
