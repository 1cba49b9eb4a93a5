"""Agents and the baselines that combine them. Generators, encoders and judges plug in; the defaults are deterministic."""
