"""The methods that the two-phase fit is compared with."""
