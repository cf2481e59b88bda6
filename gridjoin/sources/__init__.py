"""Tables and the workloads made of them."""
