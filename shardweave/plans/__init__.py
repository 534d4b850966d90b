"""Whole plans: builders, the merge, and the strategies it is compared with."""
