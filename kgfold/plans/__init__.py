"""Fixtures, the whole pipeline and the experiment workloads."""
