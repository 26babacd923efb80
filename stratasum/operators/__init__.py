"""The methods and the operators around them."""
