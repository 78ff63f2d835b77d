"""couponspark: distinct counting with coupon-matrix sketches on Spark DataFrames."""
