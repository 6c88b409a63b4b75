"""Steps of the method as DataFrame operators."""
