"""Complex columns as pairs of double columns."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, functions as F


@dataclass
class Cx:
    re: Column
    im: Column

    @classmethod
    def of(cls, name: str) -> Cx:
        return cls(F.col(f"{name}_re"), F.col(f"{name}_im"))

    def __add__(self, o: Cx) -> Cx:
        return Cx(self.re + o.re, self.im + o.im)

    def __sub__(self, o: Cx) -> Cx:
        return Cx(self.re - o.re, self.im - o.im)

    def __mul__(self, o: Cx) -> Cx:
        return Cx(self.re * o.re - self.im * o.im, self.re * o.im + self.im * o.re)

    def scale(self, k) -> Cx:
        return Cx(self.re * k, self.im * k)

    def times_j(self) -> Cx:
        return Cx(-self.im, self.re)

    def conj(self) -> Cx:
        return Cx(self.re, -self.im)

    def power(self) -> Column:
        return self.re * self.re + self.im * self.im

    def named(self, name: str) -> list[Column]:
        return [self.re.alias(f"{name}_re"), self.im.alias(f"{name}_im")]
