"""Tables and the observation frames that workloads make of them."""
