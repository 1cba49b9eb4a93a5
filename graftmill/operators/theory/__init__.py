"""Computable theory: information measures, scoring rules, garbling, gradient-descent bounds, control of agent systems."""
