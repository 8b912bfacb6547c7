"""Plan building blocks shared by the operators: staging, distributed ranks, components."""
