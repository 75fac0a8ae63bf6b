"""Sizing, probe strategies and the experiment workloads."""
