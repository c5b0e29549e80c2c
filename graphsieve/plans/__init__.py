"""Templates and the rules derived from them; all of it small and on the driver."""
