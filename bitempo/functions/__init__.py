"""Column functions: time axis, canonical values, text."""
