"""How a grid is cut and coded: specifications, targets, layouts."""
