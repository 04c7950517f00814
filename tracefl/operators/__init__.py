"""Generic DataFrame operators in the roles that the detector gives them."""
