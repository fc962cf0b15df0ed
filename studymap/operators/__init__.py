"""Vote, layer, rule, calibration, simulation and evaluation operators."""
