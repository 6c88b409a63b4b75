"""cyclefold: fold long recordings of a repeating motion into one clean cycle, on Spark."""
