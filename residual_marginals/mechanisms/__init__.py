"""Release mechanisms: adaptive, batch, direct, graphical, multiplicative weights."""
