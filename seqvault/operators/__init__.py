"""Distributed building blocks: barriers, ranks and running sums without a global window."""
