"""DataFrame operators: splitting, pools, schemes, costs, protocol."""
