"""Whole detectors, baselines and experiment workloads, composed of operators."""
